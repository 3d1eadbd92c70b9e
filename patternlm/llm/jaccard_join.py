"""N-gram Jaccard self-join by token-combination prefixes.

A token is the 64-bit hash of a shingle of k words; a document is its set of tokens. Sets that are equal form a class, and only class
representatives go on. With similarity t a set x can miss at most D = |x| - ceil(t|x|) tokens of a partner. All sets are sorted in one
global order: rare tokens first, then frequent ones. Rare tokens are indexed singly; frequent tokens fall into classes and are indexed
by pairs within a class. The prefix grows until (rare tokens) + sum over classes of (tokens - 1) exceeds D: then two similar sets share
a rare token or a pair of frequent ones inside both prefixes, whatever the counts were, so which tokens count as frequent
sets the cost and never the result. The number of classes grows with the size of the set (a scheme per power of four; sets near a border are
indexed under both), which keeps the pairs linear in the prefix.

Candidates: in each key's group all members meet one hub, the member that shares most keys; verified links join classes into
components. What remains are pairs of different components in a group. Where few members lie outside the group's main component (`direct`), they
meet all others. Elsewhere the key grows by one more token: members are indexed by the group's hub together with a token in which they differ
from it, over prefixes of those differences (see grown_pairs). Two members that do not link through the hub must share such a
token, so no link between different components is lost, and a large group of near copies that each differ in their own way forms no pairs. A pair first meets by the eighth of its tokens with the lowest hashes, which bounds its overlap from above; what the
bound leaves is verified by intersecting the whole sets.

Null and blank texts have no set and link with nothing; rows without an id take no part and have no component. Repeated rows are
equal sets. Extra columns are ignored (keep_one keeps them), whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternlm.llm.common import column, whole_row
from patternlm.llm.components import components
from patternlm.llm.text_kernel import mix64, pieces, shingle_sets
from patternlm.session import cut

FREQUENT = 16  # a token that so many documents have counts as frequent
MOST_FREQUENT = 1 << 18  # of those, the most frequent so many: the bound of the broadcast (2 MB)
COUNT_RUN = 1 << 20  # tokens held at once in a scanning task
BITS = 1 << 24
PRIME = (1 << 31) - 1
LOW = np.uint64(1 << 61)
FEW = 64  # a group whose members outside its main component meet at most FEW * FEW others is paired directly
EACH = 8  # so is a larger one with at most so many members outside: each other member meets at most so many


def needed(n: int, num: int, den: int) -> int:
    """The least overlap of a set of n tokens with a partner: ceil(t n)."""
    return -(-num * n // den)


def _long(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


SCAN = "doc_id long, n long, s1 long, s2 long, bucket int, low binary"


def _scan_sets(k: int, region: np.uint64, buckets: int):
    """A row of size and signature for each document; and, for each run of tokens, by bucket: those of the region, and those that it holds twice."""
    names = ["doc_id", "n", "s1", "s2", "bucket", "low"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        seen: set[tuple[int, int]] = set()
        size = 0

        def by_bucket(tokens: np.ndarray, rows: np.ndarray, first: int) -> tuple[list[int], list[bytes]]:
            of = (mix64(tokens + np.uint64(5)) % np.uint64(buckets)).astype(np.int32)
            order = np.argsort(of, kind="stable")
            present, starts = np.unique(of[order], return_index=True)
            return [first + int(x) for x in present], [x.tobytes() for x in np.split(rows[order], starts[1:])] if len(rows) else []

        def dealt() -> pa.RecordBatch:
            tokens, counts = np.unique(np.concatenate([np.zeros(0, np.uint64), *held]), return_counts=True)
            low = np.repeat(tokens[tokens < region], counts[tokens < region])
            twice = counts > 1
            b1, x1 = by_bucket(low, low, 0)
            b2, x2 = by_bucket(tokens[twice], np.stack([tokens[twice], counts[twice].astype(np.uint64)], 1), buckets)
            none = pa.nulls(len(b1) + len(b2), pa.int64())
            return pa.RecordBatch.from_arrays([none, none, none, none, pa.array(b1 + b2, pa.int32()), pa.array(x1 + x2, pa.binary())], names)

        for batch in pieces(batches):
            n, s1, s2 = [], [], []
            for tokens in shingle_sets(batch.column(1), k):
                a = int(np.add.reduce(tokens)) if len(tokens) else 0
                b = int(np.bitwise_xor.reduce(mix64(tokens + np.uint64(77)))) if len(tokens) else 0
                n.append(len(tokens)), s1.append(a), s2.append(b)
                if (a, b) not in seen:
                    seen.add((a, b))
                    held.append(tokens)
                    size += len(tokens)
                if size > COUNT_RUN:
                    yield dealt()
                    held.clear(), seen.clear()
                    size = 0
            m = len(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(_long(np.array(s1, np.uint64))), pa.array(_long(np.array(s2, np.uint64))), pa.nulls(m, pa.int32()), pa.nulls(m, pa.binary())], names)
        yield dealt()

    return run


def _count_tokens(buckets: int):
    """Tokens of a partition that occur often; all rows of a bucket are in the partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low, twice = [np.zeros(0, np.uint64)], [np.zeros((0, 2), np.uint64)]
        for batch in batches:
            for bucket, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                x = np.frombuffer(blob.as_buffer(), np.uint64)
                (low.append(x) if bucket < buckets else twice.append(x.reshape(-1, 2)))
        tokens, counts = np.unique(np.concatenate(low), return_counts=True)
        keep = counts >= FREQUENT
        pairs = np.concatenate(twice)
        others, place = np.unique(pairs[:, 0], return_inverse=True)
        sums = np.bincount(place, weights=pairs[:, 1].astype(float), minlength=len(others)).astype(np.int64)
        more = sums >= 2 * FREQUENT
        ids, n = np.concatenate([tokens[keep], others[more]]), np.concatenate([counts[keep], sums[more]])
        yield pa.RecordBatch.from_arrays([pa.array(_long(ids)), pa.array(n.astype(np.int64))], ["id", "n"])

    return run


def frequent_tokens(scanned: DataFrame, buckets: int) -> np.ndarray:
    """The most frequent tokens, sorted: in the region by exact counts over all documents, elsewhere by what runs hold at least twice."""
    blobs = scanned.where("bucket IS NOT NULL").select("bucket", "low").repartition(buckets, F.expr(f"bucket % {buckets}"))
    often = blobs.mapInArrow(_count_tokens(buckets), "id long, n long").groupBy("id").agg(F.max("n").alias("n")).orderBy(F.desc("n"), "id").limit(MOST_FREQUENT)
    return np.sort(often.select("id").toPandas()["id"].to_numpy(np.int64).view(np.uint64))


def scheme(n: int) -> int:
    return (int(n).bit_length() - 1) // 2


def prefix_keys(tokens: np.ndarray, frequent: np.ndarray, num: int, den: int) -> tuple[np.ndarray, int]:
    """The index keys of a set (sorted distinct tokens): rare tokens in order, then pairs; and how many are rare."""
    n = len(tokens)
    errors = n - needed(n, num, den)
    common = np.isin(tokens, frequent, assume_unique=True) if len(frequent) else np.zeros(n, bool)
    rare = tokens[~common][: errors + 1]
    keys = []
    want = errors + 1 - len(rare)
    if want > 0:
        others = tokens[common]
        for q in range(scheme(needed(n, num, den) or 1), scheme(n * den // num) + 1):
            classes = (others >> np.uint64(17)) % np.uint64(max(1, 4**q // 16))
            again = np.ones(len(others), np.int64)
            again[np.unique(classes, return_index=True)[1]] = 0
            upto = int(np.searchsorted(np.cumsum(again), want)) + 1
            part, of = others[:upto], classes[:upto]
            order = np.argsort(of, kind="stable")
            part, of = part[order], of[order]
            cuts = np.flatnonzero(np.diff(of)) + 1
            for run in np.split(part, cuts):
                i, j = np.triu_indices(len(run), 1)
                keys.append(mix64(mix64(run[i] + np.uint64(2 * q + 3)) + run[j]))
    return np.concatenate([mix64(rare ^ np.uint64(1)), np.unique(np.concatenate([np.zeros(0, np.uint64), *keys]))]), len(rare)


def low_tokens(tokens: np.ndarray) -> np.ndarray:
    """The tokens in the lowest eighth of the hash space (tokens are sorted)."""
    return tokens[: int(np.searchsorted(tokens, LOW))]


def _scan_keys(k: int, frequent: np.ndarray, num: int, den: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            found, low = [], []
            for t in shingle_sets(batch.column(1), k):
                found.append(prefix_keys(t, frequent, num, den) if len(t) else (np.zeros(0, np.uint64), 0))
                low.append(low_tokens(t).tobytes())
            lengths = np.cumsum([0, *(len(x) for x, _ in found)]).astype(np.int32)
            flat = pa.array(_long(np.concatenate([np.zeros(0, np.uint64), *(x for x, _ in found)])))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r for _, r in found], pa.int32()), pa.ListArray.from_arrays(pa.array(lengths), flat), pa.array(low, pa.binary())], ["rep", "rare", "keys", "low"])

    return run


def _places(ids: np.ndarray) -> Iterator[np.ndarray]:
    low = ids % PRIME
    for a, b in ((48271, 11), (69621, 23)):
        yield (low * a + b) % PRIME % BITS


def _scan_chosen(k: int, bits: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            hit = np.ones(len(ids), bool)
            for p in _places(ids):
                hit &= (bits[p >> 5] >> (p & 31)) & 1 == 1
            some = batch.filter(pa.array(hit))
            sets = [t.tobytes() for t in shingle_sets(some.column(1), k)]
            yield pa.RecordBatch.from_arrays([some.column(0), pa.array(sets, pa.binary())], ["rep", "tokens"])

    return run


def _common(x: pa.Scalar, y: pa.Scalar) -> tuple[int, int, int]:
    """Tokens of x, of y, and of both."""
    x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
    if not len(x) or not len(y):
        return len(x), len(y), 0
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    return len(x), len(y), int((y[at] == x).sum())


def _verified(num: int, den: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            met = [_common(x, y) for x, y in zip(batch.column(2), batch.column(3), strict=True)]
            ok = [den * both >= num * (nx + ny - both) for nx, ny, both in met]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ok, pa.bool_())], ["a", "b", "linked"])

    return run


def _possible(num: int, den: int):
    """Pairs that their low tokens leave possible: those in common and all others of the smaller remainder must reach the overlap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for x, y, nx, ny in zip(batch.column(2), batch.column(3), batch.column(4).to_pylist(), batch.column(5).to_pylist(), strict=True):
                lx, ly, both = _common(x, y)
                ok.append((num + den) * (both + min(nx - lx, ny - ly)) >= num * (nx + ny))
            yield batch.select([0, 1]).filter(pa.array(ok, pa.bool_()))

    return run


def possible(pairs: DataFrame, keyed: DataFrame, reps: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs (a, b) that may be similar, judged exactly by an eighth of their tokens."""
    known = keyed.select("rep", "low").join(reps, "rep")
    one = pairs.join(known.select(F.col("rep").alias("b"), F.col("low").alias("y"), F.col("n").alias("ny")), "b")
    two = one.join(known.select(F.col("rep").alias("a"), F.col("low").alias("x"), F.col("n").alias("nx")), "a")
    return two.select("a", "b", "x", "y", "nx", "ny").mapInArrow(_possible(num, den), "a long, b long").distinct()


def verify(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """pairs (a, b) with `linked`, from their whole sets."""
    one = pairs.join(sets.select(F.col("rep").alias("b"), F.col("tokens").alias("y")), "b")
    two = one.join(sets.select(F.col("rep").alias("a"), F.col("tokens").alias("x")), "a")
    return two.select("a", "b", "x", "y").mapInArrow(_verified(num, den), "a long, b long, linked boolean")


def _bits(reps: DataFrame) -> np.ndarray:
    """A bitmap of fixed size (2 MB) over the ids; it only spares work, the exact join follows."""
    low = F.pmod(F.col("rep"), F.lit(PRIME))
    p = reps.select(F.explode(F.array(*(F.expr("0") + (low * a + b) % PRIME % BITS for a, b in ((48271, 11), (69621, 23))))).alias("p"))
    words = p.groupBy(F.shiftright("p", 5).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 31 as int))")).alias("bits")).toPandas()
    out = np.zeros(BITS >> 5, np.int64)
    out[words["w"].to_numpy(np.int64)] = words["bits"].to_numpy(np.int64)
    return out


def index(keyed: DataFrame, reps: DataFrame) -> DataFrame:
    """Index entries (key, rep, n, pos, hub, hub_n, hub_pos) of keys that at least two classes have; pos counts the rare tokens before.

    A pair of frequent tokens follows all rare tokens of its set: were one of those in common, the two sets would meet under it first.
    """
    entries = keyed.select("rep", "rare", "keys").join(reps, "rep").select("rep", "n", "rare", F.posexplode("keys").alias("pos", "key"))
    entries = entries.select("rep", "n", F.least("pos", "rare").alias("pos"), "key")
    shared = entries.groupBy("key").agg(F.count("*").alias("members")).where("members > 1")
    met = cut(entries.join(shared, "key"), "join-entries")
    central = met.groupBy("rep").agg(F.count("*").alias("central"))
    best = F.max(F.struct(F.col("central"), (-F.col("rep")).alias("rep"), "n", "pos")).alias("best")
    hub = met.join(central, "rep").groupBy("key").agg(best)
    return cut(met.join(hub.select("key", (-F.col("best")["rep"]).alias("hub"), F.col("best")["n"].alias("hub_n"), F.col("best")["pos"].alias("hub_pos")), "key"), "join-index")


def _may_link(nx: str, px: str, ny: str, py: str, num: int, den: int):
    """Whether sets of these sizes may be similar with the key as their first common one: every earlier token of a prefix is one missed."""
    nx, px, ny, py = map(F.col, (nx, px, ny, py))
    overlap = F.ceil((nx + ny) * num / (num + den) - 1e-9)
    return (den * F.least(nx, ny) >= num * F.greatest(nx, ny)) & (px <= nx - overlap) & (py <= ny - overlap)


def fetch(texts: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """The whole sets of the members of pairs: (rep, tokens)."""
    members = pairs.select(F.col("a").alias("rep")).union(pairs.select("b")).distinct()
    sets = texts.mapInArrow(_scan_chosen(k, _bits(members)), "rep long, tokens binary")
    return cut(sets.join(members, "rep", "left_semi").dropDuplicates(["rep", "tokens"]), "join-sets")


def direct(others: Column, members: Column) -> Column:
    """Whether a group is paired directly: at most FEW * FEW pairs, or at most EACH for a member."""
    return (others <= min(EACH, FEW)) | (others * members <= FEW * FEW)


def few_pairs(rest: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (a, b) of different components in groups with few members outside their main component: linear in the group."""
    x = rest.where("comp <> main AND rep <> hub").select("key", F.col("rep").alias("a"), F.col("comp").alias("ca"), F.col("n").alias("na"), F.col("pos").alias("pa"))
    y = rest.where("rep <> hub").select("key", F.col("rep").alias("b"), F.col("comp").alias("cb"), F.col("n").alias("nb"), F.col("pos").alias("pb"), (F.col("comp") == F.col("main")).alias("mainly"))
    once = F.col("mainly") | (F.col("a") < F.col("b"))
    cross = x.join(y, "key").where((F.col("ca") != F.col("cb")) & once & _may_link("na", "pa", "nb", "pb", num, den))
    return cross.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


DELTA = "hub long, rep long, far boolean, gone int, came int, margin long, prefix array<long>"


def _differences(num: int, den: int, frequent: np.ndarray):
    """For (hub, rep, tokens of hub, tokens of rep): whether the two do not link (`far`) and a prefix of the tokens that only one of them has.

    Order: tokens that the hub lacks, rare ones before frequent ones, then the hub's own, which many members lack; by hash inside each.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            far, gone, came, margin, found = [], [], [], [], []
            for h, x in zip(batch.column(2), batch.column(3), strict=True):
                h, x = np.frombuffer(h.as_buffer(), np.uint64), np.frombuffer(x.as_buffer(), np.uint64)
                lost, new = np.setdiff1d(h, x, assume_unique=True), np.setdiff1d(x, h, assume_unique=True)
                by, size = num * (len(h) + len(new)) - den * (len(h) - len(lost)), len(lost) + len(new)
                common = np.isin(new, frequent, assume_unique=True) if len(frequent) else np.zeros(len(new), bool)
                least = (num * len(new) + den * len(lost)) // (num + den) + 1
                least = min(least, -(-by // den)) if by > 0 else least
                far.append(by > 0), gone.append(len(lost)), came.append(len(new)), margin.append(by)
                found.append(np.concatenate([mix64(new[~common] + np.uint64(2)), mix64(new[common] + np.uint64(2)), mix64(lost + np.uint64(1))])[: max(0, size - least + 1)])
            lengths = np.cumsum([0, *map(len, found)]).astype(np.int32)
            flat = pa.array(_long(np.concatenate([np.zeros(0, np.uint64), *found])))
            columns = [batch.column(0), batch.column(1), pa.array(far, pa.bool_()), pa.array(gone, pa.int32()), pa.array(came, pa.int32()), pa.array(margin, pa.int64()), pa.ListArray.from_arrays(pa.array(lengths), flat)]
            yield pa.RecordBatch.from_arrays(columns, ["hub", "rep", "far", "gone", "came", "margin", "prefix"])

    return run


def grown_pairs(rest: DataFrame, texts: DataFrame, frequent: np.ndarray, k: int, num: int, den: int) -> DataFrame:
    """Pairs (a, b) that may link in groups with many members outside the main component: one more token is combined with the group's key.

    With t = num/den and against the group's hub h, a member m lacks gone(m) tokens of h and has came(m) others; together they are its delta.
    The overlap of x and y is |h| - gone(x) - gone(y) + s and their union |h| + came(x) + came(y) - s, s the tokens that both deltas have. If x
    does not link with h (it is far: margin(x) = t(|h| + came(x)) - (|h| - gone(x)) > 0), x and y can only link when
    s >= (margin(x) + t came(y) + gone(y)) / (1 + t), so without a token in common among their deltas they do not link at all; and if neither is far,
    both link with h. So the group is indexed again by (hub, token of the delta), over prefixes of the deltas in one order of all tokens: a far
    member needs at least margin(x) common tokens whatever y is, any member more than (t came(y) + gone(y)) / (1 + t). Nothing is dropped: every
    pair that links and is not in one component by its hub shares a token of both prefixes.
    """
    members = cut(rest.where("rep <> hub").select("hub", "rep").distinct(), "join-members")
    none = members.select(F.col("hub").alias("a"), F.col("rep").alias("b")).limit(0)
    if members.isEmpty():
        return none
    sets = fetch(texts, members.select(F.col("hub").alias("a"), F.col("rep").alias("b")), k)
    met = members.join(sets.select("rep", F.col("tokens").alias("y")), "rep").join(sets.select(F.col("rep").alias("hub"), F.col("tokens").alias("x")), "hub")
    deltas = cut(met.select("hub", "rep", "x", "y").mapInArrow(_differences(num, den, frequent), DELTA), "join-deltas")
    close = deltas.where("NOT far").select(F.least("hub", "rep").alias("a"), F.greatest("hub", "rep").alias("b"))
    size, reach = F.col("gone") + F.col("came"), F.floor((num * F.col("came") + den * F.col("gone")) / (num + den) + 1e-9) + 1
    at = deltas.select("*", size.alias("size"), reach.alias("reach"), F.posexplode("prefix").alias("pos", "token")).drop("prefix")
    x = at.where(F.col("far") & (F.col("pos") <= F.col("size") - F.ceil(F.col("margin") / den - 1e-9))).select("hub", "token", F.col("rep").alias("a"), F.col("margin").alias("ma"), F.col("size").alias("za"), F.col("pos").alias("pa"))
    y = at.where(F.col("pos") <= F.col("size") - F.col("reach")).select("hub", "token", F.col("rep").alias("b"), "gone", "came", F.col("size").alias("zb"), F.col("pos").alias("pb"))
    s = F.ceil((F.col("ma") + num * F.col("came") + den * F.col("gone")) / (num + den) - 1e-9)
    pairs = x.join(y, ["hub", "token"]).where((F.col("a") != F.col("b")) & (F.col("pa") <= F.col("za") - s) & (F.col("pb") <= F.col("zb") - s))
    return close.unionByName(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))).distinct()


def jaccard_join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 3, num: int = 90, den: int = 100) -> DataFrame:
    """Every row of docs: doc_id, n_shingles, class_id (smallest id of its equal sets), component_id (smallest id that links reach)."""
    texts = docs.select(column(id_col).cast("long").alias("doc_id"), column(text_col).cast("string").alias("text"))
    buckets = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    region = np.uint64((1 << 64) * (den - num) * 5 // (den * 4))  # somewhat more of the hash space than prefixes reach
    scanned = cut(texts.mapInArrow(_scan_sets(k, region, buckets), SCAN), "join-scan")
    frequent = frequent_tokens(scanned, buckets)
    rows = scanned.where("bucket IS NULL").select("doc_id", "n", "s1", "s2")
    classes = cut(rows.where("n > 0 AND doc_id IS NOT NULL").groupBy("n", "s1", "s2").agg(F.min("doc_id").alias("rep")), "join-classes")
    reps = classes.select("rep", "n")
    held = texts.where("doc_id IS NOT NULL")

    keyed = held.mapInArrow(_scan_keys(k, frequent, num, den), "rep long, rare int, keys array<long>, low binary")
    keyed = cut(keyed.join(reps.select("rep"), "rep", "left_semi"), "join-keys")
    entries = index(keyed, reps)
    star = entries.where("rep <> hub").where(_may_link("n", "pos", "hub_n", "hub_pos", num, den))
    star = star.select(F.least("hub", "rep").alias("a"), F.greatest("hub", "rep").alias("b")).distinct()
    tried = cut(star, "join-tried")
    star = cut(possible(tried, keyed, reps, num, den), "join-pairs")
    star = cut(verify(star, fetch(held, star, k), num, den), "join-star")
    links = star.where("linked").select("a", "b")
    comps = components(links)

    labelled = entries.join(comps.withColumnRenamed("node", "rep"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    sums = labelled.groupBy("key", "comp").agg(F.count("*").alias("c"))
    mixed = sums.groupBy("key").agg(F.max(F.struct("c", "comp")).alias("most"), F.count("*").alias("comps"), F.sum("c").alias("members")).where("comps > 1")
    mixed = mixed.select("key", F.col("most")["comp"].alias("main"), direct(F.col("members") - F.col("most")["c"], F.col("members")).alias("direct"))
    rest = cut(labelled.join(mixed, "key"), "join-rest")
    cross = cut(few_pairs(rest.where("direct"), num, den).unionByName(grown_pairs(rest.where("NOT direct"), held, frequent, k, num, den)).distinct(), "join-cross")
    cross = cut(possible(cross.join(tried, ["a", "b"], "left_anti"), keyed, reps, num, den), "join-pairs")
    more = cut(verify(cross, fetch(held, cross, k), num, den).where("linked"), "join-cross")
    if not more.isEmpty():
        comps = components(links.union(more.select("a", "b")))

    known = classes.join(comps.withColumnRenamed("node", "rep"), "rep", "left").select("n", "s1", "s2", "rep", F.coalesce("comp", "rep").alias("comp"))
    out = rows.join(known, ["n", "s1", "s2"], "left")
    own = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("rep", "doc_id")).alias("class_id"), own.alias("component_id"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of docs that stay: of each group of linked documents, those with the smallest id. Rows without an id stay."""
    joined = jaccard_join(docs, id_col, **options)
    gone = joined.where("component_id <> doc_id").select(F.col("doc_id").alias("id")).distinct()
    return docs.select(whole_row(docs).alias("row"), column(id_col).cast("long").alias("id")).join(gone, "id", "left_anti").select("row.*")
