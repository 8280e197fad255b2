import pyarrow as pa

from colpick.llm.common import portions


def test_portions_keep_every_text_in_order():
    texts = ["a" * 10, None, "", "é" * 40, "b", None, "c" * 9] * 5
    for limit in (1, 10, 64, 1 << 20):
        parts = list(portions(pa.array(texts), limit))
        assert [t for p in parts for t in p] == texts
        assert all(parts)
        assert all(sum(len((t or "").encode()) + 1 for t in p[:-1]) <= limit + max(len((t or "").encode()) + 1 for t in texts) for p in parts)
    assert list(portions(pa.array([], pa.string()))) == []
    assert list(portions(pa.array([None, None], pa.string()))) == [[None, None]]
