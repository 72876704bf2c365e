"""Exact deduplication by 128-bit content hash, with a byte comparison inside every group.

1. Every text is normalised (each run of ASCII white space becomes one space; null counts as empty)
   and hashed; only 16-byte hashes and ids are shuffled, with partial aggregation, so a text that a
   third of all rows share costs one row for each map task.
2. Only texts whose hash occurs twice or more are moved; they are grouped by hash *and* bytes.
   A group of copies again collapses before the shuffle.
3. Where two different texts share a hash (never seen with 128 bits, forced in tests by a weak
   hash), the rows of that hash are matched by their bytes instead of by their hash.

Defined results: null and empty texts (and texts that differ in white space only by kind or length)
are equal; a repeated row (same id and text) forms a group of its own copies, and ``kept`` is true for
each row that carries the smallest id; rows whose id is null group by text, and an id that is not
null is preferred as ``keep_id``; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from statewitness.llm.bounded import BROADCAST_KEYS, drop_keys, keep_keys
from statewitness.llm.scratch import Scratch

SPACE_RUN = r"[\x20\x09-\x0D]+"


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_RUN, " ")


def md5_key(text: Column) -> Column:
    return F.unhex(F.md5(text))


def exact_groups(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    content_key: Callable[[Column], Column] = md5_key,
    broadcast_keys: int = BROADCAST_KEYS,
) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256 (of the normalised text)."""
    spark = docs.sparkSession
    texts = docs.select(F.col(id_col).alias("_id"), normalised(F.col(text_col)).alias("_t")).withColumn("_k", content_key(F.col("_t")))
    s = Scratch(spark)
    keyed = s.save(texts.select("_id", "_k", F.unhex(F.sha2("_t", 256)).alias("_sha")), "keyed", keep=True)
    counted = keyed.groupBy("_k").agg(F.count("*").alias("_n"))
    repeated = s.save(counted.filter("_n > 1").select("_k"), "repeated")
    n_repeated = repeated.count()
    moved = keep_keys(texts, repeated, "_k", n_repeated, broadcast_keys)
    exact = s.save(
        moved.groupBy("_k", "_t").agg(F.min("_id").alias("_keep"), F.count("*").alias("_size")).withColumn("_sha2", F.unhex(F.sha2("_t", 256))).drop("_t"),
        "exact",
        keep=True,
    )
    clashing = s.save(exact.groupBy("_k").agg(F.count("*").alias("_n")).filter("_n > 1").select("_k"), "clashing", keep=True)
    n_clashing = clashing.count()
    if n_clashing:
        clean = exact.join(clashing, "_k", "left_anti")
        rest = keep_keys(keyed, clashing, "_k", n_clashing, broadcast_keys).select("_k").distinct()
        sound = keyed.join(rest, "_k", "left_anti").join(clean, "_k", "left")
        clash_rows = keep_keys(texts, clashing, "_k", n_clashing, broadcast_keys).select("_id", "_k", "_t")
        clash_groups = clash_rows.groupBy("_k", "_t").agg(F.min("_id").alias("_keep"), F.count("*").alias("_size"))
        unsound = clash_rows.join(clash_groups, ["_k", "_t"]).withColumn("_sha", F.unhex(F.sha2("_t", 256)))
        rows = sound.select("_id", "_sha", "_keep", "_size").unionByName(unsound.select("_id", "_sha", "_keep", "_size"))
    else:
        rows = keyed.join(exact.drop("_sha2"), "_k", "left").select("_id", "_sha", "_keep", "_size")
    s.drop("repeated")
    size = F.coalesce("_size", F.lit(1).cast("long"))
    keep = F.when(F.col("_size").isNull(), F.col("_id")).otherwise(F.col("_keep"))
    return rows.select(
        F.col("_id").alias(id_col),
        keep.alias("keep_id"),
        size.alias("group_size"),
        F.col("_id").eqNullSafe(keep).alias("kept"),
        F.lower(F.hex("_sha")).alias("text_sha256"),
    )


def keep_first(docs: DataFrame, content_key: Callable[[Column], Column] = md5_key, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """The rows of ``docs`` with one of each text: the smallest id that is not null, and one of rows that repeat it.

    Only texts whose hash occurs twice or more are moved; they are grouped by hash and bytes.
    """
    s, names = Scratch(docs.sparkSession), docs.columns
    text = normalised(F.col("text").cast("string"))
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"), F.col("doc_id").alias("_id"), text.alias("_t")).withColumn("_k", content_key(F.col("_t")))
    repeated, seen = s.save_seen(keyed.groupBy("_k").agg(F.count("*").alias("_n")).filter("_n > 1").select("_k"), "repeated", keep=True)
    single = drop_keys(keyed, repeated, "_k", seen["n"], broadcast_keys)
    order = F.struct(F.col("_id").isNull().alias("none"), F.col("_id").alias("id"), F.to_json("_row").alias("json"))
    first = keep_keys(keyed, repeated, "_k", seen["n"], broadcast_keys).groupBy("_k", "_t").agg(F.min_by("_row", order).alias("_row"))
    return single.select("_row.*").unionByName(first.select("_row.*"))


def query(spark, sf_dir: str) -> DataFrame:
    return exact_groups(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


ORACLE = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY norm) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY norm) AS kept, sha256(norm) AS text_sha256
FROM t
"""
