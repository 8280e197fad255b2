import corpus_pipeline
import pyarrow as pa

from colpick.llm import near_copies
from colpick.llm.common import pieces, small_batches


def test_pieces_hold_all_rows():
    texts = ["a" * 300, None, "", "é" * 200, "b" * 900, "c"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(6)), pa.array(texts)], names=["k", "t"])
    for limit in (1, 100, 500, 10**6):
        got = list(pieces([batch, batch.slice(0, 0), batch], 1, limit=limit))
        assert pa.Table.from_batches(got).column("t").to_pylist() == 2 * texts
        assert all(b.num_rows == 1 or sum(len((t or "").encode()) + 1 for t in b.column(1).to_pylist()[:-1]) <= limit for b in got)


def test_near_copies_take_a_batch_of_long_texts_in_pieces():
    texts = pa.array([f"{i} " + "some words " * 100_000 for i in range(12)])
    batch = pa.RecordBatch.from_arrays([pa.array([bytes([i]) for i in range(12)]), texts], names=["tk", "text"])
    for kernel in (near_copies._sets(5), near_copies._sign(5)):
        sizes = [b.num_rows for b in kernel(iter([batch]))]
        assert len(sizes) >= 3 and sum(sizes) == 12


def test_stages_send_few_rows_at_a_time(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    try:
        docs = spark.createDataFrame([(1, "a b c"), (2, "d")], "doc_id long, text string")
        spark.conf.set(name, "10000")
        assert sorted(r.doc_id for r in corpus_pipeline.STAGES[1][1](spark, docs, "").collect()) == [1, 2]
        assert spark.conf.get(name) == "1000"
        spark.conf.set(name, "7")
        small_batches(spark)
        assert spark.conf.get(name) == "7"  # fewer stay fewer
    finally:
        spark.conf.set(name, before)
