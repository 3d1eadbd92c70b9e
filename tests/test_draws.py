"""Free draws from a count model are those of the whole distribution, without making it."""

import random
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_search import random_model  # noqa: E402

from patternlm.operators.model import NextTokenModel  # noqa: E402
from patternlm.plans import workloads as wl  # noqa: E402


def test_draws_equal_those_of_the_distribution():
    rng = random.Random(11)
    for _ in range(20):
        m = random_model(rng, 30)
        for ctx in [(-1,), (-1, 1, 2), (-1, 9, 9), (-1, 3)]:
            tokens, p, _, _, order = NextTokenModel.distribution(m, ctx)
            assert [t for t, _ in m.likeliest(ctx)] == [int(tokens[j]) for j in order]
            assert m.known_mass(ctx) == pytest.approx(float(p.sum()))
            for i in range(50):
                u = wl.uniform(42, i, 0)
                left = u * float(p.sum())
                for j in order:
                    left -= p[j]
                    if left < 0:
                        break
                assert wl._drawn(m, ctx, u, None) == int(tokens[j])


def test_no_distribution_of_a_long_context_is_made(monkeypatch):
    m = random_model(random.Random(3), 30)
    asked = []
    whole = type(m).probabilities
    monkeypatch.setattr(type(m), "probabilities", lambda self, ctx: asked.append(ctx) or whole(self, ctx))
    for i in range(50):
        wl._drawn(m, (-1, 1, 2), wl.uniform(42, i, 0), None)
    assert set(asked) <= {()}


def test_searches_are_dealt_to_many_tasks(spark):
    from patternlm.operators.traverse import run_many, tasks
    from patternlm.plans.query import PatternQuery

    tok = wl.Tokenizer([], "ab")
    found = run_many(spark, spark.range(40).withColumnRenamed("id", "query_id"), lambda row: PatternQuery("a|b", encoding="all"), random_model(random.Random(1), 2), tok)
    assert found.rdd.getNumPartitions() == tasks(spark) > 1 and found.count() == 40
