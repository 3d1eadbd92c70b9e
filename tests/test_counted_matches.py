"""Matches are counted beyond any cap: as many as a search without a limit lists, and more than a thousand of an input."""

import random
import sys
from collections import Counter
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_automata import random_regex, random_tokenizer  # noqa: E402
from test_search import random_model  # noqa: E402

from patternlm.operators.model import CountModel  # noqa: E402
from patternlm.operators.traverse import count_matches, lower, run_query  # noqa: E402
from patternlm.plans import workloads as wl  # noqa: E402
from patternlm.plans.query import PatternQuery, Rules, edits  # noqa: E402
from patternlm.queries import experiments as ex  # noqa: E402


def test_counts_equal_the_whole_search():
    rng = random.Random(4)
    for n in range(80):
        tok = random_tokenizer(rng)
        q = PatternQuery(random_regex(rng, 2), random_regex(rng, 1) if n % 2 else "", "all", Rules(top_k=rng.choice([None, 2, 3])), preprocessors=(edits(1, "abc"),) if n % 3 else (), max_tokens=rng.choice([3, 4]), alphabet="abc", require_eos=n % 5 == 0)
        m = random_model(rng, len(tok.vocab))
        assert count_matches(lower(q, tok, lazy=True).dfa, m, q) == Counter(r[9] for r in run_query(q, m, tok))


def test_amplification_counts_more_than_a_thousand_matches_of_an_input(spark, monkeypatch):
    import public_tokenizers

    tok = wl.PublicTokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    word = "aaaaaaaaaaaa"
    parts = {"a" * k for k in range(1, 13)} & set(tok.vocab)
    path = [-1, *tok.encode(word), -2]
    counts = {(): Counter([tok.vocab[p] for p in parts] + [t for t in path if t != -1])}
    monkeypatch.setattr(ex, "_toxic_model", lambda *_: (CountModel(counts, 1, len(tok.vocab)), tok))
    monkeypatch.setattr(wl, "toxic_inputs", lambda s, d: s.createDataFrame([(1, word, "", "")], "query_id long, sentence string, hit string, prompt string"))
    row = ex.q_tox_ampl(spark, "").first()
    assert row["n"] >= tok.count_encodings(word) > 1000 and row["plain"] == 1 and row["gain"] == row["n"]
