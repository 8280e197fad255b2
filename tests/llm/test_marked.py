"""Rows that surely aren't needed are left out before anything is moved."""

from pyspark.sql import functions as F

from colpick.llm import near_copies, simhash
from colpick.llm.common import marked, text_key


def test_marked_parts_are_whole_and_the_first_has_all_that_is_needed(spark):
    rows = spark.range(5000).select(F.when(F.col("id") % 7 > 0, F.col("id")).alias("k"), F.col("id").cast("string").alias("_part"))
    needed = rows.where("k is null or k % 50 = 1").select("k").distinct()
    likely, rest = marked(rows, needed, "k")
    assert sorted(likely.union(rest).collect(), key=str) == sorted(rows.collect(), key=str)
    assert rest.join(needed, rest.k.eqNullSafe(needed.k), "left_semi").isEmpty()
    few = rows.where("k is null or k % 50 = 1").count()
    assert few <= likely.count() < few + 5000 // 8
    assert marked(rows, needed, "k", most=1) is None
    assert marked(rows, needed.limit(0), "k")[0].isEmpty()


def shuffled(frame) -> int:
    """Rows that the exchanges of the executed plan wrote."""
    plan, seen = frame._jdf.queryExecution().executedPlan().toString(), 0
    assert "isFinalPlan" in plan
    todo = [frame._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if name == "ShuffleQueryStageExec":
            todo.append(node.plan())
            continue
        if name == "ShuffleExchangeExec":
            seen += node.metrics().apply("shuffleRecordsWritten").value()
        todo += [node.children().apply(i) for i in range(node.children().size())]
    return seen


def test_the_kept_rows_move_only_what_may_be_dropped(spark):
    docs = spark.range(4000).select(F.col("id").alias("doc_id"), F.concat(F.lit("text "), (F.col("id") % 3900).cast("string")).alias("text"))
    rows = docs.select("doc_id", text_key(F.col("text")).alias("tk"))
    kept = simhash.least_rows(docs, rows, rows.withColumn("root", F.col("tk")), "doc_id", "text")
    assert sorted(r.doc_id for r in kept.collect()) == list(range(3900))
    assert shuffled(kept) < 1000


def test_set_frame_has_the_needed_texts_once(spark):
    texts = spark.range(3000).select(F.concat(F.lit("a b c d e f "), (F.col("id") % 1000).cast("string")).alias("text")).select(text_key(F.col("text")).alias("tk"), "text")
    needed = texts.where("substring(text, 13) in ('5', '77', '901')").select("tk").distinct()
    got = near_copies._set_frame(texts, needed, 5).collect()
    assert {bytes(r.tk) for r in got} == {bytes(r.tk) for r in needed.collect()} and len(got) == 3
