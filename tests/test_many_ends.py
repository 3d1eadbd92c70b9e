"""Of many tokens that end a string only the leading ones are pushed, with the results of the whole search."""

import math
import random
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_search import random_model  # noqa: E402

from patternlm.operators import traverse as tr  # noqa: E402
from patternlm.plans import workloads as wl  # noqa: E402
from patternlm.plans.query import PatternQuery, Rules  # noqa: E402


def test_a_limit_over_many_ends_gives_the_head_of_the_whole_search(monkeypatch):
    monkeypatch.setattr(tr, "MANY", 2)
    rng = random.Random(12)
    words = [f" {a}{b}" for a in "abcd" for b in "abcd"] + ["x"]
    tok = wl.Tokenizer([], vocab={w: i for i, w in enumerate(words)})
    for n in range(40):
        m = random_model(rng, len(words))
        q = PatternQuery("( [ab][abcd]){1,2}( [abcd]{2})?", "x", "all", Rules(top_k=rng.choice([None, 5])), max_tokens=rng.choice([3, 4]), alphabet="abcdx ")
        dfa = tr.lower(q, tok).dfa
        whole = [(m_.order_cost, m_.tokens) for m_ in tr.best_first(dfa, m, q)]
        for k in (1, 3, 9):
            got = [(m_.order_cost, m_.tokens) for m_ in tr.best_first(dfa, m, q, limit=k)]
            assert [g[1] for g in got] == [w[1] for w in whole[:k]] and all(math.isclose(a[0], b[0], abs_tol=1e-9) for a, b in zip(got, whole, strict=False))


def test_ends_are_asked_once_for_queries_that_the_model_forgets(spark):
    said = spark.createDataFrame([(f"key {k} on May {d}",) for k in range(300) for d in (k % 7, k % 5)], "s string")
    model, tok = wl.chunk_model(said, "s", 2)
    asked, whole = [], type(model).ruled
    model.ruled = lambda ctx, tokens, rules: asked.append(len(tokens)) or whole(model, ctx, tokens, rules)
    for k in range(20):
        rows = tr.run_query(PatternQuery(" May [0-9]{1,3}", f"key {k} on", "all"), model, tok, 3)
        assert len(rows) == 3 and rows[0][7].startswith(" May ")
    assert sum(n > 100 for n in asked) == 1
