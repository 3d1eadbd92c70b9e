"""Edit positions of whole neighbourhoods: counted as the automaton of edits lists them, for words of any length."""

import random
from collections import Counter

from __spark_entry__ import queries
from patternlm.operators import measures as ms
from patternlm.queries.automata import ABC26, near


def first_difference(w, t):
    return next((i + 1 for i, (a, b) in enumerate(zip(w, t, strict=False)) if a != b), min(len(w), len(t)) + 1)


def test_counts_equal_the_listed_neighbours(spark):
    rng = random.Random(9)
    words = {"a", "aa", "ab", "aab", "abba", "bbbb", *("".join(rng.choice("abc") for _ in range(rng.randint(1, 7))) for _ in range(30))}
    want = Counter(first_difference(w, t) for w in words for _, t, n in near(w, 1) if n)
    got = ms.neighbour_positions(spark.createDataFrame([(w,) for w in words], "w string"), "w", len(ABC26)).collect()
    assert {r["edit_pos"]: r["n"] for r in got} == want
    assert all(r["share"] == round(r["n"] / sum(want.values()), 6) for r in got)


def test_words_of_any_length_count(spark, tmp_path):
    spark.createDataFrame([(1, "a longest Word ab", "en"), (2, "zzzzzzzzzzzz", "de")], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["edit_pos"]: r["n"] for r in queries()["q_edit_pos"](spark, str(tmp_path)).collect()}
    assert set(got) == set(range(1, 9)) and got[8] == 26 and got[1] == 4 * 51
