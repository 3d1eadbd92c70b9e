"""Regular expressions, automata, token automata: against brute force on random small languages, and worked examples."""

import itertools
import random
import re
import string

import pytest

from patternlm.functions import automata as fa
from patternlm.functions.regex import RegexError, parse, required_literals
from patternlm.functions.tokenizer import Tokenizer
from patternlm.operators import graph

STRINGS = ["".join(x) for n in range(6) for x in itertools.product("abc", repeat=n)]


def random_regex(rng, depth):
    k = rng.random()
    if depth == 0 or k < 0.3:
        return rng.choice(["a", "b", "c", "[ab]", "[^a]", "."])
    if k < 0.55:
        return random_regex(rng, depth - 1) + random_regex(rng, depth - 1)
    if k < 0.75:
        return f"({random_regex(rng, depth - 1)}|{random_regex(rng, depth - 1)})"
    return f"({random_regex(rng, depth - 1)})" + rng.choice(["*", "+", "?", "{1,2}", "{2}"])


def language(dfa, n=5):
    return {"".join(p) for p in fa.enumerate_language(dfa, n)}


def test_random_languages_against_re():
    rng = random.Random(5)
    for _ in range(120):
        r = random_regex(rng, 4)
        dfa = fa.compile_regex(r, alphabet="abc")
        expected = {s for s in STRINGS if re.fullmatch(r, s)}
        assert language(dfa) == expected
        counts = fa.walks(dfa, 5)
        assert counts[5][0] == len(expected)
        if len(expected) < 200:
            assert {"".join(fa.unrank(dfa, counts, i)) for i in range(len(expected))} == expected


def test_algebra():
    rng = random.Random(6)
    for _ in range(60):
        x, y = random_regex(rng, 3), random_regex(rng, 3)
        a, b = fa.compile_regex(x, alphabet="abc"), fa.compile_regex(y, alphabet="abc")
        la, lb = language(a), language(b)
        assert language(fa.intersect(a, b)) == la & lb
        assert language(fa.union(a, b)) == la | lb
        assert language(fa.difference(a, b)) == la - lb
        assert language(fa.complement(a, "abc")) == set(STRINGS) - la
    assert language(fa.concat(fa.words_dfa(["a", "bb"]), fa.words_dfa(["c"]))) == {"ac", "bbc"}


def test_finiteness_and_bad_patterns():
    assert fa.is_finite(fa.compile_regex("a{2,3}|b")) and not fa.is_finite(fa.compile_regex("ab*"))
    for bad in ("(a", "a)", "[a", "*a"):
        with pytest.raises(RegexError):
            fa.compile_regex(bad)
    assert required_literals(parse("[a-z]+://www[.]x")) == "://www.x"


def test_edits_of_a_word():
    def near(words, letters):
        out = set()
        for w in words:
            out |= {w} | {w[:i] + w[i + 1 :] for i in range(len(w))} | {w[:i] + c + w[i + 1 :] for i in range(len(w)) for c in letters} | {w[:i] + c + w[i:] for i in range(len(w) + 1) for c in letters}
        return out

    for word, letters, one, two in (("cat", "act", 19, 130), ("cat", string.ascii_lowercase, 180, 14206), ("ab", "ab", 9, 26)):
        first = fa.edited(fa.words_dfa([word]), 1, letters)
        assert language(first) == near({word}, letters) and len(language(first)) == one
        second = language(fa.edited(fa.words_dfa([word]), 2, letters), 6)
        assert second == near(near({word}, letters), letters) and len(second) == two
        assert second == language(fa.edited(first, 1, letters), 6)  # chaining
    assert first.finals[first.run("ab")] == 0 and first.finals[first.run("bb")] == 1


def test_erase_exclude_synonyms():
    assert language(fa.erased(fa.compile_regex("a(b)?c"), ["b"])) == {"abc", "ac"}
    arcs, finals = fa.synonym_arcs({"big": ["large"]}, string.ascii_lowercase + " ")
    assert language(fa.transduced(fa.words_dfa(["big cat"]), arcs, finals), 12) == {"big cat", "large cat"}


def test_walk_weights_of_four_strings():
    dfa = fa.compile_regex("a|b|bb|bbb")
    w = fa.walks(dfa, 5)[5]
    b = dfa.edges[0]["b"]
    assert w[0] == 4 and w[b] == 3 and w[dfa.edges[0]["a"]] == 1
    star = fa.compile_regex("a*")
    assert fa.walks(star, 5)[5][0] == 6 and [row[0] for row in fa.walks_by_length(star, 5)] == [1] * 6


def random_tokenizer(rng):
    tokens, merges = list("abc"), []
    for _ in range(rng.randint(1, 5)):
        m = (rng.choice(tokens), rng.choice(tokens))
        if m not in merges and m[0] + m[1] not in tokens:
            merges.append(m)
            tokens.append(m[0] + m[1])
    return Tokenizer(merges, "abc", chunk=None)


def test_token_automata():
    rng = random.Random(7)
    for _ in range(100):
        dfa, tok = fa.compile_regex(random_regex(rng, 4), alphabet="abc"), random_tokenizer(rng)
        strings = language(dfa)
        canonical = {tok.encode(s) for s in strings}
        short = lambda d: {p for p in fa.enumerate_language(d, 5) if len(tok.decode(p)) <= 5}  # noqa: B023, E731
        full = short(graph.compile_full(dfa, tok))
        assert {tok.decode(p) for p in full} == strings
        assert len(full) == sum(tok.count_encodings(s) for s in strings)
        assert all(tok.count_encodings(s) <= 2 ** max(len(s) - 1, 0) for s in strings)
        assert short(graph.compile_rewritten(dfa, tok)) == canonical == {p for p in full if tok.is_canonical(p)}
        if fa.is_finite(dfa):
            assert short(graph.compile_enumerated(dfa, tok, 5)) == canonical
        check = graph.pair_check(tok)
        assert all(check(p[:i]) for p in canonical for i in range(len(p) + 1))


def test_six_tokens_and_repeated_merge():
    six = Tokenizer([], vocab={t: i for i, t in enumerate(("T", "h", "e", "Th", "he", "The"))})
    assert six.count_encodings("The") == 4
    full = graph.compile_full(fa.words_dfa(["The"]), six)
    assert sum(map(len, full.edges)) == 6
    t = Tokenizer([("t", "h"), ("th", "e")], "the", chunk=None)
    assert [t.text[i] for i in t.encode("theth")] == ["the", "th"]


def test_zones():
    dfa = fa.compile_regex("(cat|dog)", "a ")
    assert [dfa.zone(s, c) for s, c in ((0, "a"), (1, " "))] == ["prefix", "prefix"]
    tok = Tokenizer([("a", " "), ("a ", "c")], "acatdog ", chunk=None)
    loose, sealed = graph.compile_full(dfa, tok), graph.compile_full(dfa, tok, seal_boundary=True)
    across = tok.vocab["a c"]
    assert across in loose.edges[0] and (0, across) not in loose.prefix and across not in sealed.edges[0]


def test_lazy_edits_make_only_the_states_that_are_read():
    base = fa.compile_regex("ab c", "(x|y)")
    for d in (1, 2):
        for scope in ("both", "prefix", "body"):
            whole, lazy = fa.edited(base, d, "abcxyz ", scope), fa.edited(base, d, "abcxyz ", scope, lazy=True)
            todo, seen = [(0, 0)], set()
            while todo:
                a, b = todo.pop()
                if (a, b) in seen:
                    continue
                seen.add((a, b))
                steps = lazy.edges[b]
                assert whole.finals.get(a) == lazy.finals.get(b) and set(whole.edges[a]) == set(steps)
                assert {c for c in steps if (a, c) in whole.prefix} == {c for c in steps if (b, c) in lazy.prefix}
                todo += [(whole.edges[a][c], t) for c, t in steps.items()]
    long = fa.edited(fa.compile_regex("a" * 300), 1, "abc ", lazy=True)
    at = 0
    for c in "aaa":
        at = long.edges[at][c]
    assert len(long._sets) < 40
