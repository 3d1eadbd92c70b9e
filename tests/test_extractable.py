"""Whether an input has a match is found without a search in order, and is what the search gives."""

import random
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_automata import random_regex, random_tokenizer  # noqa: E402
from test_search import random_model  # noqa: E402

from patternlm.operators import traverse as tr  # noqa: E402
from patternlm.operators.graph import pair_check  # noqa: E402
from patternlm.plans import workloads as wl  # noqa: E402
from patternlm.plans.query import PatternQuery, Rules, edits  # noqa: E402
from patternlm.queries import experiments as ex  # noqa: E402


def test_a_match_is_seen_where_the_search_finds_one():
    rng, seen = random.Random(8), [0, 0]
    for n in range(300):
        tok = random_tokenizer(rng) if n % 3 else wl.Tokenizer([("a", "b"), ("ab", "c"), ("b", "c"), ("c", " "), (" ", "a")], "abc '")
        pre = (edits(1, "abc"),) if n % 2 == 0 else ()
        head = random_regex(rng, 2) if n % 4 else "".join(rng.choice("abc") for _ in range(6))
        q = PatternQuery(random_regex(rng, 2), head, "canonical", Rules(top_k=rng.choice([1, 1, 2, 3])), preprocessors=pre, max_tokens=rng.choice([2, 4, 8]), alphabet="abc", require_eos=n % 5 == 0)
        queries, models = [q, q.but(encoding="all")], [random_model(rng, len(tok.vocab)), random_model(rng, len(tok.vocab))]
        want = [[bool(tr.run_query(x, m, tok, 1)) for m in models] for x in queries]
        assert tr.extractable(queries, models, tok, pair_check(tok)) == want
        for yes in (y for row in want for y in row):
            seen[yes] += 1
    assert min(seen) > 50


def test_no_search_in_order_is_made_for_success(spark, sf, monkeypatch):
    def refuse(*a, **k):
        raise AssertionError("a search")

    found = {r["setting"]: (r["queries"], r["successes"], r["success"]) for r in ex.q_tox_success(spark, sf).collect()}
    model, tok = ex._toxic_model(spark, sf, 3)
    inputs = [r.asDict() for r in wl.toxic_inputs(spark, sf).collect()]
    want = {}
    for name, s in (("canonical", ("prompted", "canonical", 0)), ("all + edits", ("prompted", "all", 1))):
        n = sum(bool(tr.run_query(wl.toxic_query(r, *s), model, tok, 1)) for r in inputs)
        want[name] = (len(inputs), n, round(n / len(inputs), 6))
    assert found == want
    monkeypatch.setattr(tr, "best_first", refuse)
    asked = [wl.toxic_query(inputs[0], "prompted", "all", 1)]
    assert tr.extractable(asked, [model], tok, pair_check(tok)) == [[bool(tr.any_match(tr.lower(asked[0], tok, lazy=True).dfa, model, asked[0]))]]


def test_a_space_that_belongs_to_the_next_word_ends_no_canonical_path():
    import public_tokenizers

    tok = wl.PublicTokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    ok, rng = pair_check(tok), random.Random(3)
    assert not ok((tok.vocab[" "], tok.vocab["oren"]))
    for _ in range(3000):
        e = tok.encode("".join(rng.choice(["a", "b", "on", " ", "  ", " of", "'s", "'", "\n", "\t", "1", ".", "-"]) for _ in range(rng.randint(1, 9))))
        assert all(ok(e[:i]) for i in range(2, len(e) + 1))
