"""Merkle fixity audit of record archives and their replicas.

A record is a key, a SHA-256 and a length. The primary's records, in key order, lie at byte offsets; `range_bytes` of offsets make a range,
a leaf of its tree. The manifest keeps each range's first record, and replicas fall into ranges by it, so a record that is damaged, lost or
added changes its own range and none after it. Leaves hash their ordered records, inner nodes their `fanout` children, up to one root.
Roots are compared first; below a node whose hashes agree nothing is read again; only records of mismatching leaves are compared.

Payloads are hashed where they are read; shuffles carry digests only, and equal records are counted before them. Order and offsets come
from a range partitioning and two levels of sums, never from one task. Null keys sort first, null payloads are empty, repeated
records count (a replica with fewer copies misses them), empty archives have no root and agree with each other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternlm.session import cut

RANGE_BYTES = 1 << 18
FANOUT = 16
RUN = 1024


def warc_record(uri: Column, payload: Column) -> Column:
    """A record of an archive: header lines, the payload, two line ends."""
    payload, uri = F.coalesce(payload, F.lit("")), F.coalesce(uri, F.lit(""))
    head = F.concat(F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Target-URI: "), uri, F.lit("\r\nContent-Length: "), F.octet_length(payload).cast("string"), F.lit("\r\n\r\n"))
    return F.concat(head, payload, F.lit("\r\n\r\n"))


def digests(archive: DataFrame, key: str, record: Column) -> DataFrame:
    """(key, sha, length, copies) of the distinct records of an archive."""
    one = archive.select(F.col(key).alias("key"), record.alias("r")).select("key", F.sha2(F.col("r").cast("binary"), 256).alias("sha"), F.octet_length("r").cast("long").alias("length"))
    return one.groupBy("key", "sha", "length").agg(F.count("*").alias("copies"))


def ordered(rows: DataFrame, by: list[str], name: str) -> DataFrame:
    """rows as a table with their place: `part` (ranges of the order) and `pos` (ascending inside a part)."""
    spread = rows.repartitionByRange(*by).sortWithinPartitions(*by)
    return cut(spread.withColumn("part", F.spark_partition_id()).withColumn("pos", F.monotonically_increasing_id()), name)


def offsets(primary: DataFrame) -> DataFrame:
    """Adds `offset`: the bytes of all records before, by sums over runs, parts and all parts."""
    runs = primary.withColumn("run", F.expr(f"pos div {RUN}"))
    size = F.col("length") * F.col("copies")
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    held = runs.groupBy("part", "run").agg(F.sum(size).alias("held"))
    parts = held.groupBy("part").agg(F.sum("held").alias("held"))
    part_base = parts.select("part", F.coalesce(F.sum("held").over(before(Window.orderBy("part"))), F.lit(0)).alias("part_base"))
    run_base = held.select("part", "run", F.coalesce(F.sum("held").over(before(Window.partitionBy("part").orderBy("run"))), F.lit(0)).alias("run_base"))
    own = F.coalesce(F.sum(size).over(before(Window.partitionBy("part", "run").orderBy("pos"))), F.lit(0))
    placed = runs.withColumn("own", own).join(run_base, ["part", "run"]).join(part_base, "part")
    return placed.withColumn("offset", F.col("own") + F.col("run_base") + F.col("part_base")).drop("own", "run", "run_base", "part_base")


def manifest(placed: DataFrame, range_bytes: int) -> DataFrame:
    """range -> its first record (key, sha)."""
    first = F.min(F.struct("key", "sha")).alias("first")
    return placed.withColumn("range", F.expr(f"offset div {range_bytes}")).groupBy("range").agg(first).select("range", "first.key", "first.sha")


def in_ranges(rows: DataFrame, bounds: DataFrame, name: str) -> DataFrame:
    """rows with the last range that begins at or before them (0 before the first): an as-of join by one ordering of both."""
    both = rows.withColumn("begins", F.lit(None).cast("long")).withColumn("is_row", F.lit(1)).unionByName(bounds.select("key", "sha", F.col("range").alias("begins"), F.lit(0).alias("is_row")), allowMissingColumns=True)
    placed = ordered(both, ["key", "sha", "is_row"], name)
    parts = placed.groupBy("part").agg(F.max("begins").alias("most"))
    earlier = F.max("most").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    parts = parts.select("part", F.coalesce(earlier, F.lit(0)).alias("earlier"))
    latest = F.max("begins").over(Window.partitionBy("part").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0))
    out = placed.withColumn("latest", latest).where("is_row = 1").join(F.broadcast(parts), "part")  # a row per partition
    return out.withColumn("range", F.coalesce("latest", "earlier")).drop("latest", "earlier", "begins", "is_row")


def _hash_of(*parts: Column) -> Column:
    listed = F.transform(F.sort_array(F.collect_list(F.struct(*(p.alias(f"p{i}") for i, p in enumerate(parts))))), lambda s: F.concat_ws(":", *(s[f"p{i}"].cast("string") for i in range(len(parts)))))
    return F.sha2(F.array_join(listed, "\n").cast("binary"), 256)


def runs_of(rows: DataFrame) -> DataFrame:
    """rows (with part and pos of `ordered`) with `nth`, the place of a record in its range, and `run`; no range is ordered in one task."""
    index = F.expr("pos & 8589934591")  # within the part
    parts = rows.groupBy("part").agg((F.max(index) + 1).alias("held"))
    parts = parts.select("part", F.coalesce(F.sum("held").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    placed = rows.join(F.broadcast(parts), "part").withColumn("at", F.col("base") + index).drop("base")  # a row per partition
    first = placed.groupBy("range").agg(F.min("at").alias("first"))
    return placed.join(first, "range").withColumn("nth", F.col("at") - F.col("first")).withColumn("run", F.expr(f"nth div {RUN}")).drop("at", "first")


def leaves(runs: DataFrame, rounds: int) -> DataFrame:
    """Level 0 hashes that depend on a range's records and their order alone, not on how they were partitioned.

    Runs of records are hashed first, then runs of such hashes, `rounds` times: a range of any length (a replica may hold many records beyond the last
    one of the primary) never meets in one task before few hashes are left of it. Both archives take the same number of rounds.
    """
    key = F.coalesce(F.col("key").cast("string"), F.lit(""))
    h = runs.groupBy("range", "run").agg(_hash_of(F.col("nth"), key, F.col("sha"), F.col("copies")).alias("h"))
    for _ in range(rounds):
        h = h.groupBy("range", F.expr(f"run div {RUN}").alias("above")).agg(_hash_of(F.col("run"), F.col("h")).alias("h")).withColumnRenamed("above", "run")
    return h.groupBy("range").agg(_hash_of(F.col("run"), F.col("h")).alias("hash")).select(F.lit(0).alias("level"), F.col("range").alias("node"), "hash")


def tree(leaf: DataFrame, depth: int, fanout: int = FANOUT) -> list[DataFrame]:
    """Levels from the leaves to the root."""
    levels = [leaf]
    for level in range(1, depth + 1):
        below = levels[-1].select(F.expr(f"node div {fanout}").alias("parent"), "node", "hash")
        levels.append(below.groupBy("parent").agg(_hash_of(F.col("node"), F.col("hash")).alias("hash")).select(F.lit(level).alias("level"), F.col("parent").alias("node"), "hash"))
    return levels


def descend(one: list[DataFrame], two: list[DataFrame], fanout: int = FANOUT) -> DataFrame:
    """Leaves whose hashes differ, reached only through differing parents."""
    suspects = None
    for a, b in zip(reversed(one), reversed(two), strict=True):
        if suspects is not None:
            under = suspects.select(F.col("node").alias("parent"))
            a, b = (x.join(under, F.expr(f"node div {fanout}") == F.col("parent"), "left_semi") for x in (a, b))
        met = a.select("node", F.col("hash").alias("x")).join(b.select("node", F.col("hash").alias("y")), "node", "full")
        suspects = cut(met.where(~F.col("x").eqNullSafe(F.col("y"))).select("node"), "merkle-suspects")
        if suspects.isEmpty():
            break
    return suspects


def depth_of(ranges: int, fanout: int) -> int:
    depth = 0
    while ranges > 1:
        ranges, depth = -(-ranges // fanout), depth + 1
    return depth


def audit(primary: DataFrame, replica: DataFrame, key: str, record: Column, range_bytes: int = RANGE_BYTES, fanout: int = FANOUT) -> DataFrame:
    """Every distinct record of either archive: key, range, offset, length, copies, status (ok, corrupt, missing, extra)."""
    own = offsets(ordered(digests(primary, key, record), ["key", "sha"], "merkle-primary"))
    own = cut(own.withColumn("range", F.expr(f"offset div {range_bytes}")), "merkle-offsets")
    bounds = manifest(own, range_bytes)
    other = cut(in_ranges(digests(replica, key, record), bounds, "merkle-replica"), "merkle-ranges")
    last = bounds.agg(F.max("range")).first()[0]  # one number
    depth = depth_of((last or 0) + 1, fanout)
    pair = [cut(runs_of(r), "merkle-runs") for r in (own, other)]
    longest = max((r.agg(F.max("run")).first()[0] or 0) for r in pair)  # one number each
    one, two = ([cut(x, "merkle-level") for x in tree(leaves(r, depth_of(longest + 1, RUN)), depth, fanout)] for r in pair)
    bad = descend(one, two, fanout)
    x = own.join(bad, F.col("range") == F.col("node"), "left").withColumn("suspect", F.col("node").isNotNull()).drop("node")
    fine = x.where("NOT suspect").select("key", "range", "offset", "length", "copies", "sha", F.lit("ok").alias("status"))
    a = x.where("suspect").select("key", "sha", "range", "offset", "length", "copies")
    b = other.join(bad, F.col("range") == F.col("node"), "left_semi").select(F.col("key").alias("k2"), F.col("sha").alias("s2"), F.col("range").alias("r2"), F.col("length").alias("l2"), F.col("copies").alias("c2"))
    met = a.join(b, F.col("key").eqNullSafe(F.col("k2")) & (F.col("sha") == F.col("s2")), "full")
    keys_a, keys_b = a.select(F.col("key").alias("ka")).distinct().withColumn("in_a", F.lit(True)), b.select(F.col("k2").alias("kb")).distinct().withColumn("in_b", F.lit(True))
    met = met.withColumn("k", F.when(F.col("range").isNull(), F.col("k2")).otherwise(F.col("key")))
    met = met.join(keys_a, F.col("k").eqNullSafe(F.col("ka")), "left").join(keys_b, F.col("k").eqNullSafe(F.col("kb")), "left")
    status = F.when(F.col("range").isNotNull() & F.col("r2").isNotNull(), F.when(F.col("copies") > F.col("c2"), "missing").when(F.col("copies") < F.col("c2"), "extra").otherwise("ok"))
    status = status.when(F.col("range").isNotNull(), F.when(F.col("in_b"), "corrupt").otherwise("missing")).when(F.col("in_a"), "damaged copy").otherwise("extra")
    found = met.select(F.col("k").alias("key"), F.coalesce("range", "r2").alias("range"), "offset", F.coalesce("length", "l2").alias("length"), F.coalesce("copies", "c2").alias("copies"), F.coalesce("sha", "s2").alias("sha"), status.alias("status"))
    return fine.unionByName(found)


def root(levels: list[DataFrame]) -> DataFrame:
    return levels[-1].select("hash")
