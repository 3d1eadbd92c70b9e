"""Streams against their batch twins; sources, sinks, SQL functions."""

import shutil

from pyspark.sql import functions as F

from patternlm.operators.model import UniformModel
from patternlm.operators.traverse import MATCHES
from patternlm.plans import sqlapi
from patternlm.queries import events as twins
from patternlm.sources import io
from patternlm.streaming import stream


def event_files(spark, sf, tmp_path):
    e = io.table(spark, sf, "events")
    path = str(tmp_path / "events")
    e.repartitionByRange(6, "ts").sortWithinPartitions("ts").write.parquet(path)
    return stream.event_time(stream.read_files(spark, path, e.schema, 100), "1 hour")


def test_windows_equal_batch(spark, sf, tmp_path):
    events = event_files(spark, sf, tmp_path)
    got = {tuple(r) for r in stream.run_to_end(stream.window_counts(events, "1 day"), "w1", "complete").collect()}
    assert got == {tuple(r) for r in twins.q_tumbling(spark, sf).collect()}
    pairs = stream.run_to_end(stream.followed_by(events, "error", "signup"), "w2").collect()
    assert {tuple(r) for r in pairs} == {tuple(r) for r in twins.q_interval_join(spark, sf).collect()}


def test_dedup_and_truth(spark, sf, tmp_path):
    e = io.table(spark, sf, "events")
    path = tmp_path / "twice"
    e.coalesce(1).write.parquet(str(path))
    part = next(path.glob("part-*"))
    shutil.copy(part, path / "part-copy.parquet")
    events = stream.event_time(stream.read_files(spark, str(path), e.schema, 1), "40 days")
    once = stream.run_to_end(stream.distinct_hits(events, ["event_id"]), "d1")
    assert once.count() == e.count()
    known = spark.createDataFrame([(1,), (2,)], "user_id long")
    hits = stream.run_to_end(stream.against_truth(events, known, "user_id"), "d2")
    assert hits.count() == 2 * e.where("user_id IN (1, 2)").count()


def test_pattern_over_rows(spark, sf, tmp_path):
    events = event_files(spark, sf, tmp_path)
    letters = {"view": "v", "click": "c", "purchase": "p"}
    got = {r["event_id"] for r in stream.run_to_end(stream.spanning_pattern(events, "vc", letters), "p1").collect()}
    want, last = set(), {}
    for r in io.table(spark, sf, "events").orderBy("ts", "event_id").collect():
        if last.get(r["user_id"]) == "view" and r["event_type"] == "click":
            want.add(r["event_id"])
        last[r["user_id"]] = r["event_type"]
    assert got == want


def test_incremental_counts(spark, tmp_path):
    a = spark.createDataFrame([([1, 2],)], "tokens array<int>")
    merge = stream.update_counts(str(tmp_path / "c"), 2)
    merge(a, 0), merge(a, 1), merge(a, 1)  # a replay changes nothing
    assert spark.read.parquet(str(tmp_path / "c/1")).agg(F.min("cnt"), F.max("cnt")).first() == (2, 2)


def test_scans_sinks_and_sql(spark, sf, tmp_path):
    docs = io.table(spark, sf, "documents")
    found = stream.scan(docs).select("doc_id", "hit", "prompt").collect()
    assert all(r["hit"] in io.INSULTS for r in found)
    m = spark.createDataFrame([(1, 1, [1], "a", 1.0, -1.0, "", "a", True, 0, 1, 1)], MATCHES)
    for _ in range(2):
        io.write_matches(m, str(tmp_path / "m"))
    assert spark.read.parquet(str(tmp_path / "m")).count() == 1
    assert len(io.redacted(m).first()["body_text"]) == 64
    (tmp_path / "q.json").write_text('{"query_id": 1, "body_regex": "a*"}\n')
    assert io.json_specs(spark, str(tmp_path / "q.json")).first()["body_regex"] == "a*"
    (tmp_path / "t.txt").write_text("one\ntwo\n")
    assert io.text_lines(spark, str(tmp_path / "t.txt")).count() == 2
    (tmp_path / "t.csv").write_text("a,b\n1,x\n")
    assert io.csv_table(spark, str(tmp_path / "t.csv"), "a int, b string").first() == (1, "x")
    sqlapi.register(spark, UniformModel(26))
    assert spark.sql("SELECT * FROM regex_edges('ab|ac')").count() == 3
    assert [r["token"] for r in spark.sql("SELECT * FROM tokenize('the') ORDER BY pos").collect()] == ["the"]
    assert spark.sql("SELECT * FROM pattern_match('a|b', '', 100, 5)").count() == 2
