"""Each operator against a brute-force version on small tables with nulls, empty and long texts, ties and repeated rows."""

import bisect
import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from patternlm.llm import entry, exact_dedup, jaccard_join, language_id, license_scan, merkle_audit, mixing, packing, quality_classifier, quality_rules, secret_scan
from patternlm.llm.text_kernel import text_words

LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
WORD = re.compile(r"[^\x20\x09-\x0D]+")
LONG = " ".join(f"w{i % 701}" for i in range(30_000))
ODD = [(1, None), (2, ""), (3, " \t\n\x0b\x0c\r "), (4, "one"), (5, "ÀÉ straße İ"), (6, "àÉ straße İ"), (7, "One"), (8, LONG), (9, LONG), (None, "no id"), (4, "one"), (10, "\x00 nul   sep x"), (11, "|||"), (12, "a b"), (13, "A b")]


def rows_of(df):
    return [r.asDict() for r in df.collect()]


def words_of(text):
    return WORD.findall(text or "")


@pytest.mark.parametrize("name", ["op1_merkle_audit", "op2_license_scan", "op4_quality_rules", "op5_jaccard_join", "op9_exact_dedup"])
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = entry.queries()[name](spark, sf)
    cols = sorted(df.columns)
    rel = con.execute(entry.oracle_sql()[name])
    names = [x[0] for x in rel.description]
    want = sorted((tuple(r[names.index(c)] for c in cols) for r in rel.fetchall()), key=str)
    assert sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str) == want


def test_empty_tables(spark, docs_of):
    none = docs_of([]).limit(0)
    assert exact_dedup.exact_dedup(none).count() == 0
    assert mixing.mix(none).count() == 0 and mixing.mixed_documents(none).count() == 0
    assert quality_rules.quality_rules(none).count() == 0
    assert jaccard_join.jaccard_join(none).count() == 0
    assert secret_scan.secret_scan(none).count() == 0
    assert packing.best_fit_packing(none).count() == 0
    assert license_scan.license_scan(none).count() == 0
    assert language_id.learn_and_identify(none).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert quality_classifier.learn_and_score(none, labels).count() == 0
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    assert merkle_audit.audit(pages, pages, "page_id", merkle_audit.warc_record(F.col("url"), F.col("html"))).count() == 0


# 1 -----------------------------------------------------------------------------------------------------------------------------------


def test_merkle_audit_finds_planted_damage(spark):
    rng = random.Random(1)
    pages = [(i, f"u{i}", "x" * rng.randrange(400)) for i in range(300)] + [(None, None, None), (5, "u5", "twice"), (5, "u5", "twice"), (400, "", "z" * 50_000)]
    damaged = {7: "corrupt", 120: "missing", 299: "corrupt"}
    other = [p if damaged.get(p[0]) != "corrupt" else (p[0], p[1], "bad") for p in pages if damaged.get(p[0]) != "missing"] + [(1000, "new", "page")]
    other.remove((5, "u5", "twice"))
    a, b = (spark.createDataFrame(x, "page_id long, url string, html string").repartition(5) for x in (pages, other))
    record = merkle_audit.warc_record(F.col("url"), F.col("html"))
    found = rows_of(merkle_audit.audit(a, b, "page_id", record, range_bytes=4096, fanout=4))
    by = defaultdict(set)
    for r in found:
        by[r["status"]].add(r["key"])
    assert by["corrupt"] == {7, 299} and by["missing"] == {120, 5} and by["extra"] == {1000} and by["damaged copy"] == {7, 299}
    at = sorted((r for r in found if r["offset"] is not None), key=lambda r: r["offset"])
    place = 0
    for r in at:
        assert r["offset"] == place and r["range"] == place // 4096
        place += r["length"] * r["copies"]
    assert all(r["status"] == "ok" for r in rows_of(merkle_audit.audit(a, a, "page_id", record, range_bytes=4096)))


# 2 -----------------------------------------------------------------------------------------------------------------------------------


def test_license_scan(docs_of):
    grant = license_scan.TEMPLATES["MIT-grant"]
    w = license_scan.plain_words(grant)
    edited = " ".join(w[:30] + ["other"] + w[31:])
    cut = " ".join(w[: len(w) // 2])
    docs = [(1, "x " * 50 + grant + " tail" * 30), (2, edited), (3, cut), (4, "Released under the MIT License. " * 3), (5, "released UNDER the mit licence"), (6, (LONG + " ") * 2 + edited), *[(i + 100, t) for i, (_, t) in enumerate(ODD)]]
    got = {(r["doc_id"], r["license"]): r for r in rows_of(license_scan.license_scan(docs_of(docs)))}
    sets = {k: {tuple(x[i : i + 5]) for i in range(len(x) - 4)} for k, x in ((k, license_scan.plain_words(t)) for k, t in license_scan.TEMPLATES.items())}
    want = {}
    for i, text in docs:
        x = license_scan.plain_words(text or "")
        own = {tuple(x[j : j + 5]) for j in range(len(x) - 4)}
        for k, s in sets.items():
            if len(s & own) >= 0.8 * len(s):
                want[i, k] = len(s & own)
    assert {k: r["found"] for k, r in got.items()} == want
    assert {(1, "MIT-grant"), (2, "MIT-grant"), (4, "MIT"), (6, "MIT-grant")} <= set(got) and (3, "MIT-grant") not in got
    assert got[1, "MIT-grant"]["first_word"] == 50 and got[1, "MIT-grant"]["containment"] == 1.0
    assert license_scan.bands(0.6, 0.005) == 6


def test_license_windows_retrieve_every_template_of_enough_containment(docs_of):
    """Recall of the bands alone against exact containment, over templates of all widths with random changes."""
    rng = random.Random(12)
    vocab = [f"q{i}" for i in range(300)]
    templates = {f"t{n}": " ".join(rng.choices(vocab, k=n)) for n in (5, 6, 8, 9, 12, 20, 24, 60, 150)}
    docs, n = [], 0
    for name, text in templates.items():
        for _ in range(25):
            w = text.split()
            for _ in range(rng.randrange(1 + len(w) // 12)):
                i = rng.randrange(len(w))
                w[i : i + rng.randrange(2)] = rng.choices(vocab, k=rng.randrange(3))
            docs.append((n, " ".join(rng.choices(vocab, k=rng.randrange(30)) + w + rng.choices(vocab, k=rng.randrange(30)))))
            n += 1
    got = {(r["doc_id"], r["license"]) for r in rows_of(license_scan.license_scan(docs_of(docs), templates))}
    runs = lambda t: {tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)}
    want = {(i, k) for i, t in docs for k, x in templates.items() if len(runs(x) & runs(t)) >= 0.8 * len(runs(x))}
    assert got == want and len(want) > 100
    assert [license_scan.width_of(n, 0.8) for n in (1, 2, 4, 8, 16, 150)] == [1, 2, 2, 4, 8, 8]
    with pytest.raises(ValueError):
        license_scan.license_scan(docs_of(docs), {"short": "only four words here"})


# 3 -----------------------------------------------------------------------------------------------------------------------------------


def test_code_lengths_equal_direct_ppm():
    texts = {"a": [b"abracadabra\nabra", b"cab"], "b": [b"bananas and bandanas", b""]}
    model = language_id.train(texts, 2, 1)
    trees = {}
    for x, samples in texts.items():
        tree = defaultdict(Counter)
        for t in samples:
            padded = b"\n\n" + t
            for i in range(2, len(padded)):
                for d in range(3):
                    tree[padded[i - d : i]][padded[i]] += 1
        trees[x] = tree
    known = {c for s in texts.values() for t in s for c in t} | {10}

    def p(x, ctx, c):
        if ctx is None:
            return 1 / 256
        below = None if ctx == b"" else ctx[1:]
        f = trees[x].get(ctx)
        if not f:
            return p(x, below, c)
        n, q = sum(f.values()), len(f)
        if c in f:
            return f[c] / (n + q)
        left = 1 - sum(p(x, below, s) for s in f)
        return q / (n + q) * p(x, below, c) / left

    for text in (b"abracadabra", b"banana \xff!", b"\nx", b"c"):
        padded = b"\n\n" + text
        bits = language_id.code_lengths(model, np.frombuffer(text, np.uint8), np.array([0, len(text)]))[0]
        for k, x in enumerate(model.languages):
            assert math.isclose(bits[k], -sum(math.log2(p(x, padded[i - 2 : i], padded[i])) for i in range(2, len(padded))), rel_tol=1e-4)
    assert 255 not in known


def test_language_id_on_held_out_and_odd_rows(spark, sf, docs_of):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = language_id.learn_and_identify(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.where("lang = lang_pred").count() >= 0.95 * got.count() > 0
    odd = docs_of([*[(i + 1000, t, "en", None) for i, (_, t) in enumerate(ODD)], *[tuple(r) for r in docs.select("doc_id", "text", "lang", "source").limit(100).collect()]])
    got = {r["doc_id"]: r for r in rows_of(language_id.learn_and_identify(odd))}
    assert got[1000]["lang_pred"] == got[1001]["lang_pred"] == got[1012]["lang_pred"] == "und" and got[1000]["score"] == 0
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())
    assert {r["lang_pred"] for r in rows_of(language_id.learn_and_identify(docs_of([(1, "text"), (2, "more")])))} == {"und"}


# 4 -----------------------------------------------------------------------------------------------------------------------------------


def brute_quality(text):
    text = text or ""
    w = words_of(text)
    windows = defaultdict(list)
    for i in range(len(w) - 7):
        windows[tuple(w[i : i + 8])].append(i)
    covered = {i + k for at in windows.values() if len(at) > 1 for i in at for k in range(8)}
    lines = [x for x in text.split("\n") if words_of(x)]
    n = len(w)
    return n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered), n < 20 or 100 * len(covered) > 30 * n


def test_quality_rules(docs_of):
    rng = random.Random(2)
    rows = list(ODD)
    for i in range(60):
        base = [rng.choice("the of and x yy zzz a#b !! ünï".split()) for _ in range(rng.randrange(80))]
        rows.append((100 + i, "".join(x + rng.choice([" ", "\n", " \t"]) for x in base + (base[:15] if i % 2 else []))))
    rows += [(500, "same line here\n" * 30), (501, " ".join(f"u{i}" for i in range(20)) + " a b c d e f g h z a b c d e f g h"), (502, "k " * 1000)]
    got = rows_of(quality_rules.quality_rules(docs_of(rows)))
    key = lambda r: (r[0] is None, r[0], *map(str, r[1:]))
    have = sorted(((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in got), key=key)
    assert have == sorted(((i, *brute_quality(t)) for i, t in rows), key=key)
    assert all(not r["kept"] for r in got if r["base_failed"])


# 5 -----------------------------------------------------------------------------------------------------------------------------------


def brute_components(rows, k, num, den):
    sets = []
    for _, t in rows:
        w = words_of((t or "").translate(LOW))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set())
    ids = [i for i, _ in rows]
    parent = {i: i for i in ids if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if ids[a] is None or ids[b] is None or not sets[a] or not sets[b]:
                continue
            both = len(sets[a] & sets[b])
            if den * both >= num * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(ids[a]), find(ids[b])))
                parent[y] = x
    return sorted(((i, len(s), find(i) if i is not None else None) for i, s in zip(ids, sets, strict=True)), key=str)


@pytest.mark.parametrize(("k", "num", "den"), [(3, 90, 100), (5, 80, 100), (2, 60, 100)])
def test_jaccard_join(docs_of, monkeypatch, k, num, den):
    """Families of near copies around the threshold, a passage that many share, sets of a few tokens; with few and with many frequent tokens."""
    rng = random.Random(k)
    vocab = [f"v{i}" for i in range(400)]
    passage = " ".join(rng.choices(vocab, k=40))
    rows, n = [(i, t) for i, t in ODD if t is not LONG], 20
    for size in (30, 120, 330):
        base = rng.choices(vocab, k=size)
        for c in range(25):
            w = list(base)
            for _ in range(rng.randrange(1 + size // 25)):
                w[rng.randrange(size)] = rng.choice([*vocab, f"new{c}"])
            rows.append((n, " ".join(w).upper() if c % 3 else " ".join(w)))
            n += 1
    for c in range(40):
        rows.append((n, " ".join(rng.choices(vocab, k=rng.choice((0, 5, 60)))) + " " + passage))
        n += 1
    for c in range(40):
        rows.append((n, " ".join(rng.choices(vocab[:4], k=rng.randrange(1, 12)))))
        n += 1
    rows += rows[-5:]
    want = brute_components(rows, k, num, den)
    for frequent in (16, 3):
        monkeypatch.setattr(jaccard_join, "FREQUENT", frequent)
        got = rows_of(jaccard_join.jaccard_join(docs_of(rows).repartition(4), k=k, num=num, den=den))
        assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == want
    kept = {r["doc_id"] for r in rows_of(jaccard_join.keep_one(docs_of(rows), k=k, num=num, den=den))}
    assert kept == {c if c is not None else None for _, _, c in want}


def test_jaccard_join_pairs_of_a_group_of_near_copies_stay_linear(docs_of, monkeypatch):
    """Copies of one text that each differ in their own way: links as by brute force, with pairs for growing groups that do not grow with the square."""
    made = {}
    grown = jaccard_join.grown_pairs

    def counted(rest, *options):
        out = grown(rest, *options)
        made[size] = out.count()
        return out

    monkeypatch.setattr(jaccard_join, "grown_pairs", counted)
    for size in (60, 240):
        rng = random.Random(9)
        base, rows = rng.choices([f"v{i}" for i in range(400)], k=120), []
        for i in range(size):
            w = list(base)
            for _ in range(rng.randrange(9)):
                w[rng.randrange(len(w))] = f"n{i}x{rng.random()}"
            if i % 5 == 0:
                w = w[: 120 - rng.randrange(30)]
            rows.append((i, " ".join(w)))
        got = rows_of(jaccard_join.jaccard_join(docs_of(rows).repartition(4), k=5, num=80, den=100))
        assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == brute_components(rows, 5, 80, 100)
    assert made[240] <= 5 * made[60] + 240
    monkeypatch.setattr(jaccard_join, "FEW", 0)
    rows = [(i, " ".join(base[: 60 + i]) + f" own{i % 7} word") for i in range(60)] + [(100 + i, f"a{i} b{i} " + " ".join(base[:40])) for i in range(40)]
    got = rows_of(jaccard_join.jaccard_join(docs_of(rows).repartition(4), k=3, num=80, den=100))
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == brute_components(rows, 3, 80, 100)


def test_word_kernel_splits_like_the_pattern():
    import pyarrow as pa

    texts = [None, "", " a  b ", "A b", "é x\ty", LONG, "z"]
    got = [len(w) for w in text_words(pa.array(texts))]
    assert got == [len(words_of(t)) for t in texts]
    hashes = list(text_words(pa.array(["a b", "A b", "b a", "a"])))
    assert (hashes[0] == hashes[1]).all() and (hashes[0] == hashes[2][::-1]).all() and hashes[0][0] == hashes[3][0]


# 6 -----------------------------------------------------------------------------------------------------------------------------------


def test_quality_classifier(spark, docs_of):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = quality_classifier.learn_and_score(docs, labels).join(labels, "doc_id").where("held_out")
    assert got.where("predicted = quality").count() >= 0.95 * got.count() > 0
    odd = docs_of(ODD)
    one = rows_of(quality_classifier.learn_and_score(odd, spark.createDataFrame([(1, 1), (2, None), (None, 0)], "doc_id long, quality int")))
    assert len(one) == len(ODD) and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in one)
    rng = np.random.default_rng(0)
    x = rng.random((500, len(quality_classifier.STATISTICS)))
    y = ((x[:, 0] > 0.5) & (x[:, 1] <= 0.7)).astype(int)
    model = quality_classifier.fit(x, y)
    table = spark.createDataFrame([tuple(map(float, r)) for r in x], list(quality_classifier.STATISTICS))
    s = table.select(quality_classifier.compiled(model, F.struct(*quality_classifier.STATISTICS)).alias("s")).toPandas()["s"]
    assert ((s.to_numpy() >= 0.5) == y).mean() > 0.97 and len(model.rules) < 200


# 7 -----------------------------------------------------------------------------------------------------------------------------------


def test_secret_scan(docs_of):
    key = "AKIA" + "Q7Z2" * 4
    hot = "aZ3kP9xQ7mB2vN8cL5tR1wYhJ4"
    texts = {
        1: f"password=abcdef token: 'short' secret:\"a.b-c_d/e+f=\" API_KEY = x1y2z3 and apikey=123456", 2: key + " AKIASHORT", 3: "0123456789abcdef01234567 0123456789abcdef",
        4: f"see {hot} here", 5: "password=secret:abcdefg password=token:abcdefg", 6: "ſecret=abcdefg toKen=abcdefg", 7: "123e4567-e89b-12d3-a456-426614174000 EXAMPLEexampleKEY1234567890abcd", 8: "é" * 5 + "secret=abcdefgh",
    }
    got = {r["doc_id"]: r for r in rows_of(secret_scan.secret_scan(docs_of([*texts.items(), *[(100 + i, t) for i, (_, t) in enumerate(ODD)]])))}

    def base(text):
        out = []
        for m in re.finditer("(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", text, re.I | re.A):
            if len(m[2]) >= 6:
                out.append((m.start(), 0, f"assign:{m.start()}:{m.end()}"))
        out += [(m.start(), 1, f"access:{m.start()}:{m.end()}") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
        out += [(m.start(), 2, f"hex:{m.start()}:{m.end()}") for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
        return ",".join(x for _, _, x in sorted(out))

    for i, t in texts.items():
        assert got[i]["base_sha256"] == hashlib.sha256(base(t).encode()).hexdigest(), i
        assert set(filter(None, base(t).split(","))) <= set(got[i]["spans"].split(","))
    assert got[4]["spans"] == f"entropy_base64:4:{4 + len(hot)}" and got[7]["n_entropy"] == 0 and got[8]["spans"].startswith("assign:5:")
    assert got[100]["base_sha256"] == hashlib.sha256(b"").hexdigest() and got[107]["n_entropy"] == 0
    rng = random.Random(4)
    for _ in range(200):
        s = "".join(rng.choices("abcd0123", k=rng.randrange(1, 60)))
        hot_at = {i + j for i in range(len(s) - 11) if -sum(c / 12 * math.log2(c / 12) for c in Counter(s[i : i + 12]).values()) >= 2.5 - 1e-12 for j in range(12)}
        assert {i for a, b in secret_scan.hot_windows(s, 12, 2.5) for i in range(a, b)} == hot_at
    assert rows_of(secret_scan.redact(docs_of([(8, texts[8])])))[0]["text"] == "ééééé[secret]"


# 8 -----------------------------------------------------------------------------------------------------------------------------------


def test_packing(docs_of):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.default_tokenizer())
    rng = random.Random(3)
    rows = [*ODD, *[(200 + i, "word " * rng.randrange(3000)) for i in range(60)], (300, "<|endoftext|> x"), (301, "café " * 1022), (302, "a <|endoftext|>b <|endoftext|>")]
    got = rows_of(packing.best_fit_packing(docs_of(rows).repartition(3)))
    want = Counter()
    for i, t in rows:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        first = len(ids) % 1024 or min(1024, len(ids))
        for p, (a, b) in enumerate(zip([0, *range(first, len(ids), 1024)], [*range(first, len(ids), 1024), len(ids)], strict=True)):
            want[i, p, a, b - a, zlib.crc32(ids[a:b].tobytes())] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    seqs = defaultdict(list)
    for r in got:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    for x in seqs.values():
        at = 0
        for offset, length in sorted(x):
            assert offset == at
            at += length
        assert at <= 1024
    assert len(seqs) <= 1.02 * math.ceil(sum(r["length"] for r in got) / 1024) + 1


def best_fit_decreasing(counts, capacity):
    """How many sequences the sequential method needs."""
    gaps = []
    for length in sorted((x for x, n in counts.items() for _ in range(n)), reverse=True):
        at = bisect.bisect_left(gaps, length)
        gap = gaps.pop(at) if at < len(gaps) else capacity
        if gap > length:
            bisect.insort(gaps, gap - length)
        elif gap == length:
            pass
        best_fit_decreasing.opened += gap == capacity
    return best_fit_decreasing.opened


def test_supersteps_place_every_rank_once_and_as_densely_as_best_fit(spark):
    rng = random.Random(5)
    for n in range(5):
        counts = {rng.randrange(1, 33): rng.randrange(1, 400) for _ in range(rng.randrange(1, 12) if n else 32)}
        runs = packing.best_fit(spark.createDataFrame(list(counts.items()), "length long, n long"), 32)
        for length, n in counts.items():
            own = sorted((r[1], r[2]) for r in runs if r[0] == length)
            at = 0
            for a, c in own:
                assert a == at
                at += c
            assert at == n
        fill = defaultdict(int)
        for length, _, n, sequence, offset in sorted(map(tuple, runs), key=lambda r: (r[3], r[4])):
            for s in range(sequence, sequence + n):
                fill[s] += length
        for length, _, n, sequence, offset in runs:
            assert offset + length <= 32
        assert max(fill.values()) <= 32
        best_fit_decreasing.opened = 0
        assert len(fill) <= 1.03 * best_fit_decreasing(counts, 32) + 1
    assert len(packing.best_fit(spark.createDataFrame([], "length long, n long"), 32)) == 0


def test_a_sweep_gives_each_piece_the_narrowest_free_gap_and_settles_conflicts_by_rank(spark):
    runs = spark.createDataFrame([(packing.GAP, 10, 100, 2), (packing.GAP, 7, 200, 1), (packing.PIECES, 7, 0, 2), (packing.PIECES, 6, 0, 3), (packing.PIECES, 2, 0, 1)], "kind int, size long, first long, n long")
    pairs = {(r["length"], r["width"]): (r["rank"], r["sequence"], r["n"], r["times"]) for r in packing.successors(runs, 3).collect()}
    # the narrowest gap that holds 7 is the 7; its second piece takes a 10, the other 10 goes to a 6; two 6 and the 2 wait
    assert pairs == {(7, 7): (0, 200, 1, 1), (7, 10): (1, 100, 1, 1), (6, 10): (0, 101, 1, 1)}
    after = {(r["kind"], r["size"], r["first"], r["n"]) for r in packing.updated(runs, packing.successors(runs, 3)).collect()}
    assert after == {(packing.PIECES, 6, 1, 2), (packing.PIECES, 2, 0, 1), (packing.GAP, 3, 100, 1), (packing.GAP, 4, 101, 1)}


# 9 -----------------------------------------------------------------------------------------------------------------------------------


def test_exact_dedup(docs_of):
    rows = [*ODD, *[(1000 + i, "Copy of a text") for i in range(50)], (2000, "copy OF a text"), (2001, "ÇOPY"), (2002, "çOPY")]
    for bits, capacity in ((64, 100_000), (64, 2), (3, 1), (1, 1)):
        got = rows_of(exact_dedup.exact_dedup(docs_of(rows).repartition(4), capacity=capacity, hash_bits=bits))
        groups = defaultdict(list)
        for i, t in rows:
            groups[(t or "").translate(LOW)].append(i)
        want = Counter()
        for i, t in rows:
            g = groups[(t or "").translate(LOW)]
            keep = max((x for x in g if x is not None), default=None)
            want[i, keep, len(g), i == keep, hashlib.sha256((t or "").translate(LOW).encode()).hexdigest()] += 1
        assert Counter((r["doc_id"], r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in got) == want
    kept = rows_of(exact_dedup.drop_copies(docs_of(rows)))
    assert len(kept) == len(groups) and set(kept[0]) == {"doc_id", "text", "lang", "source", "n_chars", "key"}


def test_directory_doubles_until_no_bucket_is_overfull(spark):
    keys = spark.range(2000).select(F.xxhash64("id").alias("h"))
    slots, depth = exact_dedup.directory(keys, 50)
    d = {r["slot"]: r["bucket"] for r in slots.collect()}
    assert len(d) == slots.count() and depth >= 6
    held = Counter(d[r["s"]] for r in keys.select(exact_dedup.first_bits(F.col("h"), depth).alias("s")).collect())
    assert max(held.values()) <= 50 and sum(held.values()) == 2000
    depths = {b.bit_length() - 1 for b in held}
    assert len(depths) > 1 and all(held[b ^ 1] + n > 50 for b, n in held.items() if b ^ 1 in held)  # no bucket was split that did not need it
    close = spark.range(300).select((F.col("id") + 7).alias("h"))  # hashes that differ in their last bits only
    slots, depth = exact_dedup.directory(close, 100_000)
    assert depth == 0 and slots.count() == 1


def test_lookups_go_through_directory_bucket_and_chain(docs_of):
    rows = [(i, f"text {i % 40}") for i in range(120)]
    keys, index, slots, depth = exact_dedup.index_of(docs_of(rows), capacity=2, hash_bits=4)
    chains = index.groupBy("h").agg(F.max("chain").alias("links"), F.count("*").alias("n")).collect()
    assert sum(r["n"] for r in chains) == 40 and all(r["links"] == r["n"] for r in chains) and max(r["n"] for r in chains) > 1
    assert exact_dedup.look_up(keys, index, slots, depth).count() == 120
    wrong = slots.withColumn("bucket", F.col("bucket") + 1000)
    assert exact_dedup.look_up(keys, index, wrong, depth).count() == 0
    assert exact_dedup.look_up(keys, index.where("chain = 1"), slots, depth).count() < 120


# 10 ----------------------------------------------------------------------------------------------------------------------------------


def brute_targets(sizes):
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    total, fixed = sum(sizes.values()), {}
    while True:
        free = [s for s in order if s not in fixed]
        left = total - sum(fixed.values())
        share = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / share > 3 * sizes[s] + 1e-9]
        if not over:
            return fixed | {s: left * weight[s] / share for s in free}
        fixed |= {s: 3.0 * sizes[s] for s in over}


def test_mixing(docs_of):
    rng = random.Random(6)
    rows = [(i, " ".join(["w"] * rng.choice((0, 1, 3, 50, 700))), None, rng.choice(["b", "a", "é", None, "zz"])) for i in range(200)]
    rows += [(300, None, None, "nul"), (301, "one two", None, "tiny"), (302, LONG, None, "a"), (303, "x y z", None, "b"), (303, "x y z", None, "b"), (None, "q", None, "")]
    docs = docs_of(rows)
    got = rows_of(mixing.mix(docs, block=64))
    assert len(got) == len(rows)
    sizes, taken = Counter(), Counter()
    for r in got:
        sizes[r["source"]] += r["size"]
        taken[r["source"]] += r["taken"]
    want = brute_targets({s: sizes[s] for s in sizes})
    for r in got:
        assert r["source_size"] == sizes[r["source"]] and math.isclose(r["target"], want[r["source"]], abs_tol=1e-6) and 0 <= r["taken"] <= 3 * r["size"]
    assert all(abs(taken[s] - want[s]) <= 1 for s in want)
    again = rows_of(mixing.mix(docs.repartition(7), block=64))
    key = lambda r: str(sorted(r.items(), key=str))
    assert sorted(map(key, got)) == sorted(map(key, again))
    copies = mixing.mixed_documents(docs, block=64)
    words = copies.groupBy("source").agg(F.sum(mixing.n_words(F.col("text"))).alias("n")).collect()
    assert {r["source"]: r["n"] for r in words} == {s: n for s, n in taken.items() if n}
    assert copies.columns == docs.columns


def test_permutation_and_slots(spark):
    for n in (1, 2, 7, 64, 1000):
        p = spark.range(n).select(mixing.permuted(F.col("id"), F.lit(n).cast("long"), [F.lit("k")]).alias("x"))
        back = p.select(mixing.permuted(F.col("x"), F.lit(n).cast("long"), [F.lit("k")], inverse=True).alias("y"))
        assert sorted(r["x"] for r in p.collect()) == list(range(n)) and [r["y"] for r in back.collect()] == list(range(n))
    per = spark.createDataFrame([("1a", "a", 1000, 2500.0), ("1b", "b", 5000, 3500.0)], "skey string, source string, source_size long, target double")
    s = mixing.slots(mixing.plan(per, 10), 10, shard_slots=60)
    words = {r["source"]: r["w"] for r in s.groupBy("source").agg(F.sum("take").alias("w")).collect()}
    assert words == {"a": 2500, "b": 3500}
    assert mixing.shard_counts(s).groupBy("shard").agg(F.sum("slots").alias("n")).where("n = 60").count() >= 9


def test_shards_draw_multinomial_counts_and_the_mix_meets_targets(spark, docs_of):
    per = spark.createDataFrame([("1a", "a", 1000, 2500.0), ("1b", "b", 5000, 3500.0), ("1c", "c", 40000, 6000.0)], "skey string, source string, source_size long, target double")
    planned = mixing.plan(per, 10)
    totals = set()
    for seed in range(3):
        drawn = mixing.draws(planned, 60, seed)
        counts = {(r["shard"], r["skey"]): r["slots"] for r in mixing.shard_counts(drawn).collect()}
        assert sum(counts.values()) == 1203  # a partial epoch has a slot more, as it may meet the short block
        assert all(sum(counts.get((i, k), 0) for k in ("1a", "1b", "1c")) == 60 for i in range(20))
        for k, p in (("1a", 250 / 1200), ("1b", 350 / 1200), ("1c", 600 / 1200)):
            own = [counts.get((i, k), 0) for i in range(20)]
            assert abs(np.mean(own) - 60 * p) < 5 * math.sqrt(60 * p * (1 - p) / 20) and 0.3 < np.var(own) / (60 * p * (1 - p)) < 2.5
            totals.add((k, sum(own)))
        s = mixing.slots(planned, 10, 60, seed)
        assert {r["source"]: r["w"] for r in s.groupBy("source").agg(F.sum("take").alias("w")).collect()} == {"a": 2500, "b": 3500, "c": 6000}
        assert s.groupBy("slot").count().where("count > 1").isEmpty() and s.groupBy("source", "epoch", "block").count().where("count > 1").isEmpty()
    assert len(totals) > 3  # independent draws: totals vary with the seed
    rng = random.Random(8)
    rows = [(i, " ".join(f"d{i}w{j}" for j in range(rng.choice((1, 5, 90, 300)))), None, rng.choice("abc")) for i in range(60)]
    docs = docs_of([*rows, rows[0], rows[0]])
    blocks = rows_of(mixing.mixed_blocks(docs, block=32, shard_slots=8))
    said = Counter(int(w[1:].split("w")[0]) for r in blocks for w in r["text"].split())
    mixed = rows_of(mixing.mix(docs, block=32, shard_slots=8))
    taken, shards = Counter(), defaultdict(set)
    for r in mixed:
        taken[r["doc_id"]] += r["taken"]
    assert said == Counter({i: n for i, n in taken.items() if n})
    for r in blocks:
        for i in r["doc_ids"]:
            shards[i].add(r["shard"])
    assert all(set(r["shards"]) <= shards[r["doc_id"]] for r in mixed) and len({x for r in mixed for x in r["shards"]}) > 5
    other = {r["doc_id"]: r["shards"] for r in rows_of(mixing.mix(docs, block=32, shard_slots=8, seed=1))}
    assert any(other[r["doc_id"]] != r["shards"] for r in mixed)  # where a document goes is the draws' doing


# all ---------------------------------------------------------------------------------------------------------------------------------


def test_audit_of_a_replica_with_many_records_beyond_the_last(spark, monkeypatch):
    monkeypatch.setattr(merkle_audit, "RUN", 8)
    pages = spark.createDataFrame([(i, f"u{i}", "x" * (i % 50)) for i in range(60)], "page_id long, url string, html string")
    more = pages.unionByName(spark.createDataFrame([(1000 + i, f"v{i}", "y") for i in range(600)], pages.schema)).repartition(6)
    record = merkle_audit.warc_record(F.col("url"), F.col("html"))
    for one, two in ((pages, more), (pages.limit(0), more)):
        n = one.count()
        found = Counter(r["status"] for r in rows_of(merkle_audit.audit(one, two, "page_id", record, range_bytes=1024, fanout=4)))
        assert found == Counter({k: v for k, v in (("ok", n), ("extra", 660 - n)) if v})
    runs = merkle_audit.runs_of(merkle_audit.in_ranges(merkle_audit.digests(more, "page_id", record), merkle_audit.manifest(merkle_audit.offsets(merkle_audit.ordered(merkle_audit.digests(pages, "page_id", record), ["key", "sha"], "t")), 1024), "t"))
    assert runs.groupBy("range", "run").count().where("count > 8").isEmpty()


def test_one_very_long_text_full_of_secrets():
    import time

    text = " ".join(f"token=abcdef{i} aZ3kP9xQ7mB2vN8cL5tR1wYhJ4{i % 10}" for i in range(40_000))
    began = time.time()
    base, more = secret_scan.scan(text)
    assert len(base) == 40_000 and len(more) == 40_000 and time.time() - began < 60
    rng = random.Random(3)
    for _ in range(50):
        spans = [(a, a + rng.randrange(1, 9), "x") for a in (rng.randrange(60) for _ in range(6))]
        starts, ends = secret_scan.merged(spans)
        assert {i for a, b in zip(starts, ends, strict=True) for i in range(a, b)} == {i for a, b, _ in spans for i in range(a, b)}


def test_extra_columns_of_any_name_pass_the_filters(spark):
    import corpus_pipeline

    names = "row id digest copy out nth gone __q __broken __base __kept __gone __own __id __digest __whole size block shard a.b `x".split()
    good = "the dog and the cat run to a house in the town of a river that is old and as far as it was"
    rows = [(i, f"{good} word{i} other{i} last{i} {' '.join(f'w{i}x{j}' for j in range(40))}", "en", "s", 7, *[f"{i}{n}" for n in names]) for i in range(6)]
    rows.append((7, rows[0][1], *rows[0][2:]))
    quoted = ", ".join("`" + n.replace("`", "``") + "` string" for n in names)
    docs = spark.createDataFrame(rows, f"doc_id long, text string, lang string, source string, n_chars long, {quoted}")
    for name, stage in corpus_pipeline.STAGES[:4]:
        docs = corpus_pipeline.cut(stage(spark, docs, ""), name)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars", *names], name
    assert corpus_pipeline.STAGES[4][1](spark, docs, "").count() >= 6
    got = docs.collect()
    assert len(got) == 6 and all(r[n] == f"{r['doc_id'] % 7}{n}" for r in got for n in names)


def python_statistics(text):
    text = text or ""
    w, lines = words_of(text), [x for x in text.split("\n") if words_of(x)]
    n_words, word_chars, symbols, dup_lines, repeat, _ = brute_quality(text)
    n, m, chars = max(n_words, 1), max(len(lines), 1), max(len(text), 1)
    stops = set(" ".join(quality_rules.STOP_WORDS.values()).split())
    share = lambda pattern: len("".join(re.findall(pattern, text))) / chars
    return {
        "log_words": math.log1p(n_words), "mean_word_chars": word_chars / n, "symbols_per_word": symbols / n, "stop_word_share": sum(x in stops for x in w) / n,
        "shouted_share": sum(x.endswith("!!") for x in w) / n, "dup_line_share": dup_lines / m, "bullet_line_share": sum(bool(re.match(r"[ \t]*[-*•]", x)) for x in lines) / m,
        "ellipsis_line_share": sum(bool(re.search(r"(\.\.\.|…)[ \t\r]*$", x)) for x in lines) / m, "repeat_word_share": repeat / n, "words_per_line": n_words / m,
        "upper_share": share("[A-Z]+"), "digit_share": share("[0-9]+"), "bar_share": share(r"\|+"), "mark_share": share("[!?.,;:]+"),
    }


def test_classifier_scores_equal_the_fitted_rules_and_the_lasso_is_at_its_optimum(spark, docs_of):
    docs, labels = spark.read.parquet("/root/testdata/sf0.001/documents.parquet"), spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    x, y = quality_classifier.labelled_rows(docs, labels)
    model = quality_classifier.fit(x, y)
    assert model.rules
    rows = [(r["doc_id"], r["text"]) for r in docs.limit(60).collect()] + [(i + 10_000 if i is not None else None, t) for i, t in ODD] + [(20_000, "- A b!!\n* c…\n- A b!!\n12 | x...")]
    got = rows_of(quality_classifier.quality_classifier(docs_of(rows), model))
    want = []
    for i, t in rows:
        s = python_statistics(t)
        total = model.bias + sum(w for tests, w in model.rules if all((s[c.stat] > c.threshold) == c.above for c in tests))
        want.append((str(i), round(1 / (1 + math.exp(-total)), 9)))
    assert sorted((str(r["doc_id"]), round(r["score"], 9)) for r in got) == sorted(want)
    rng = np.random.default_rng(2)
    z = (rng.random((300, 12)) > 0.5).astype(float)
    y = (z[:, 0] + z[:, 1] * rng.random(300) > 0.8).astype(float)
    penalty = 0.01
    b, w = quality_classifier._lasso(z, y, penalty, 4000)
    r = 1 / (1 + np.exp(-(z @ w + b))) - y
    slope = z.T @ r / len(y)
    assert abs(r.mean()) < 1e-5 and np.all(np.abs(slope) <= penalty + 1e-5) and np.allclose(slope[w != 0], -penalty * np.sign(w[w != 0]), atol=1e-5) and (w == 0).any()
