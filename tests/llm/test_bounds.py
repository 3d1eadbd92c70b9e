"""Bounds on what tasks hold and on what groups pair."""

import pyarrow as pa
from pyspark.sql import functions as F

from patternlm.llm import jaccard_join
from patternlm.llm.text_kernel import PIECE, pieces


def test_a_batch_is_handed_on_in_pieces():
    texts = ["a b " * 25_000, None, ""] * 60
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts)], ["doc_id", "text"])
    out = list(pieces(iter([batch, batch.slice(5, 0)])))
    assert len(out) > 2 and max(sum(len(t or "") for t in b.column(1).to_pylist()) for b in out) <= PIECE
    assert [x for b in out for x in b.column(0).to_pylist()] == list(range(len(texts)))


def test_no_large_group_is_paired_with_many_members(spark):
    groups = spark.createDataFrame([(64, 2000), (9, 2000), (8, 2000), (64, 64), (1, 10**6)], "others long, members long")
    got = {(r["others"], r["members"]): r["direct"] for r in groups.select("*", jaccard_join.direct(F.col("others"), F.col("members")).alias("direct")).collect()}
    assert got == {(64, 2000): False, (9, 2000): False, (8, 2000): True, (64, 64): True, (1, 10**6): True}
