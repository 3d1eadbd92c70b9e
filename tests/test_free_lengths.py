"""Free samples of several stop lengths come from one draw each, and the model goes to the tasks once."""

from pyspark import SparkContext

from __spark_entry__ import queries
from patternlm.plans import workloads as wl


def test_a_draw_cut_at_a_length_is_the_draw_of_that_length(spark):
    said = spark.createDataFrame([(x,) for x in ("abab", "abc", "b", "cabba")], "s string")
    model, tok = wl.character_model(said, "s", 3)
    cut = wl.free_cuts(model, tok, "a", (1, 2, 5, 9), range(200))
    for n in (1, 2, 5, 9):
        assert [x[1:] for x in cut if x[0] == n] == wl.free_texts(model, tok, "a", n, range(200))
    ended = {x[1] for x in cut if x[0] == 2 and x[3]}
    assert ended and {x[1] for x in cut if x[0] == 1 and x[3]} < ended and all(x[3] for x in cut if x[0] > 2 and x[1] in ended)
    assert {x[2] for x in cut if x[0] == 2 and not x[3]} <= {f"a{x}{y}" for x in "abc" for y in "abc"}


def test_one_model_is_sent_for_all_stop_lengths(spark, sf, monkeypatch):
    sent, send = [], SparkContext.broadcast
    monkeypatch.setattr(SparkContext, "broadcast", lambda self, value: sent.append(value) or send(self, value))
    rows = queries()["q_free_url_n"](spark, sf).collect()
    assert len(sent) == 1 and [r["stop_length"] for r in rows] == [1, 2, 4, 8, 16, 32, 64] and {r["attempts"] for r in rows} == {10_000}
