"""Closed choices are scored by joins with counts: the numbers of the count model, without a vocabulary on the driver."""

import math

import pytest

from __spark_entry__ import queries
from patternlm.plans import workloads as wl


def test_scores_by_counts_equal_those_of_the_model(spark):
    said = spark.createDataFrame([(s,) for s in ("a b c d e", "a b c d f", "+a -b c d", "a  b c", "x", "c d e f g h")], "sentence string")
    asked = [(1, "a b", c) for c in (" c d e", " c d f", " b", " f", "")] + [(2, "a", c) for c in (" b", " -b", " c")] + [(3, "", c) for c in ("a", "+a", "x", "a b c d e f")] + [(4, "x b c d e", " f g h")]
    asked = spark.createDataFrame([(*r, len(r[2])) for r in asked], "query_id long, prompt string, choice string, extra int")
    for order in (1, 2, 3, 5):
        want = {(r["query_id"], r["choice"]): r for r in wl.score_choices(asked.where("choice <> ''"), *wl.chunk_model(said, "sentence", order)).collect()}
        scored = wl.score_by_counts(asked, said, "sentence", order)
        got = {(r["query_id"], r["choice"]): r for r in wl.ranked_choices(scored.where("choice <> ''")).collect()}
        assert got.keys() == want.keys()
        for k, r in got.items():
            assert math.isclose(r["logp"], want[k]["logp"], rel_tol=1e-12) and r["extra"] == len(r["choice"])
            assert [r[c] for c in ("n_tokens", "rnk", "mean_rnk")] == [want[k][c] for c in ("n_tokens", "rnk", "mean_rnk")]
        assert scored.where("choice = ''").select("n_tokens", "logp").first() == (0, 0.0)


def test_unknown_words_have_what_is_left(spark):
    said = spark.createDataFrame([("a b",), ("a c",)], "sentence string")
    asked = spark.createDataFrame([(1, "a", c) for c in (" b", " c", " never")], "query_id long, prompt string, choice string")
    got = {r["choice"]: math.exp(r["logp"]) for r in wl.score_by_counts(asked, said, "sentence", 2).collect()}
    model, tok = wl.chunk_model(said, "sentence", 2)
    ctx = (-1, *tok.encode("a"))
    assert got[" b"] == pytest.approx(math.exp(model.logp(ctx, tok.encode(" b")[0]))) and got[" never"] == pytest.approx(math.exp(model.logp(ctx, 99)))


def test_fewer_others_are_the_first_of_more(spark):
    said = spark.createDataFrame([(k, d, f"Customer {k} ordered on {s}") for k, d, s in ((0, 1, "May 1, 1995"), (1, 2, "May 2, 1995"), (2, 1, "May 1, 1995"), (5, 3, "May 3, 1995"))], "c_custkey long, order_date int, sentence string")
    few, more = wl.closed_choices(said, 2), wl.closed_choices(said, 5)
    assert set(few.collect()) == set(more.where("nth <= 2").collect()) and more.count() > few.count()


@pytest.mark.parametrize("name", ["q_mc_model", "q_mc_model_letters"])
def test_choices_need_no_vocabulary(spark, sf, monkeypatch, name):
    monkeypatch.setattr(wl, "MOST_PACKED", 10)
    assert queries()[name](spark, sf).count() > 0
