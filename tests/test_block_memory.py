"""A block is held once: no second matrix of its size while it is chosen from."""

import tracemalloc

import numpy as np
import pyarrow as pa

from colpick.functions import vec
from colpick.operators import distributed, kernel


def peak_of(work) -> tuple[int, object]:
    tracemalloc.start()
    try:
        out = work()
        return tracemalloc.get_traced_memory()[1], out
    finally:
        tracemalloc.stop()


def test_choice_by_rows_makes_no_second_matrix():
    x = np.random.default_rng(1).normal(size=(150_000, 32)).T
    b = x[:, :40]
    most, trace = peak_of(lambda: kernel.targeted(x, 3, b))
    assert most < x.nbytes * 0.75
    whole = np.einsum("in,in->n", x, b @ (b.T @ x)) / (x * x).sum(axis=0)
    assert trace.picks[0] == int(np.argmax(whole))


def test_block_of_many_batches_is_held_once():
    x = np.random.default_rng(2).normal(size=(150_000, 32))

    def batches():
        for at in range(0, len(x), 5000):
            # numbers of its own for each batch, as they come from a socket
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(at, at + 5000)), vec.unstack(x[at : at + 5000].copy()), pa.array(np.zeros(5000, dtype=np.int64))], names=["col_id", "vec", "block"])

    most, out = peak_of(lambda: list(distributed._kernel(4, x[:40].T, x.nbytes)(batches())))
    assert [r.num_rows for r in out] == [4]
    assert out[0].column(2).to_pylist() == kernel.targeted(x.T, 4, x[:40].T).picks
    assert most < 2 * x.nbytes
