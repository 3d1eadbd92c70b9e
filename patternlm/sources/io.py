"""Sources and sinks: tables with declared column pruning, corpora as lines, model and match stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

INSULTS = ("trash", "scum", "idiot", "clown", "moron", "loser")
MORE_INSULTS = (*INSULTS, "worthless", "pathetic", "stupid", "disgusting")
EVENT_PROPS = T.StructType([T.StructField("k", T.LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path).withColumnRenamed("value", "text")


def json_specs(spark: SparkSession, path: str) -> DataFrame:
    """Query specifications as JSON lines."""
    return spark.read.schema("query_id long, prefix_regex string, body_regex string, encoding string, top_k int, max_tokens int").json(path)


def csv_table(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("header", True).csv(path)


def sample_rows(df: DataFrame, id_col: str, fraction: float, seed: int = 42) -> DataFrame:
    """The rows whose id falls in a seeded share of the hash space: the same on every rerun, partitioning and engine. Rows without an id are left out."""
    at = F.conv(F.substring(F.md5(F.concat(F.col(id_col).cast("string"), F.lit(f":{seed}"))), 1, 8), 16, 10).cast("long")
    return df.where(at < F.lit(round(fraction * 2**32)))


def english_words(docs: DataFrame) -> DataFrame:
    """(doc_id, w): the lower-case words (runs of a-z) of English documents."""
    return docs.where("lang = 'en'").select("doc_id", F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)").alias("w"))


def sentences(docs: DataFrame) -> DataFrame:
    """(doc_id, sent_no, sentence): split at sentence marks, line ends and bars; blank pieces keep no row."""
    parts = docs.select("doc_id", F.posexplode(F.split("text", r"[.!?\n|]")).alias("sent_no", "sentence"))
    return parts.withColumn("sentence", F.btrim("sentence")).where("sentence <> ''")


def word_pattern(words: tuple[str, ...]) -> str:
    """The words with no ASCII letter on either side (no \\b: engines differ on it)."""
    return f"(^|[^a-zA-Z])({'|'.join(words)})($|[^a-zA-Z])"


def with_hits(rows: DataFrame, col: str, words: tuple[str, ...]) -> DataFrame:
    """rows whose text has a listed word, with the first `hit` and the `prompt` before it. The plain alternation filters before the exact one."""
    pattern = word_pattern(words)
    found = rows.where(F.col(col).rlike("|".join(words)) & F.col(col).rlike(pattern))
    return found.withColumn("hit", F.regexp_extract(col, pattern, 2)).withColumn("prompt", F.regexp_extract(col, f"^(.*?)({pattern})", 1)).withColumn("prompt", F.concat("prompt", F.regexp_extract(col, pattern, 1)))


def verbalised_orders(orders: DataFrame, customer: DataFrame) -> DataFrame:
    """(c_custkey, order_date, sentence): one fact for each order."""
    met = orders.select(F.col("o_custkey").alias("c_custkey"), F.to_date("o_orderdate").alias("order_date")).join(customer.select("c_custkey"), "c_custkey")
    return met.withColumn("sentence", F.concat(F.lit("Customer "), F.col("c_custkey").cast("string"), F.lit(" ordered on "), F.date_format("order_date", "MMMM d, yyyy")))


def write_matches(matches: DataFrame, path: str, buckets: int = 16) -> None:
    """An idempotent store of matches, by bucket of the query."""
    matches.withColumn("bucket", F.pmod(F.xxhash64("query_id"), F.lit(buckets))).write.partitionBy("bucket").mode("overwrite").option("partitionOverwriteMode", "dynamic").parquet(path)


def write_counts(counts: DataFrame, path: str, buckets: int = 64) -> None:
    """A model store, clustered by context so that frontiers shuffle to it and the model stays."""
    keyed = counts.withColumn("ctx_hash", F.xxhash64("ctx"))
    keyed.repartition(buckets, "ctx_hash").sortWithinPartitions("ctx_hash").write.mode("overwrite").parquet(path)


def redacted(matches: DataFrame, col: str = "body_text") -> DataFrame:
    """matches whose bodies (personal data, insults) are digests."""
    return matches.withColumn(col, F.sha2(F.col(col), 256))
