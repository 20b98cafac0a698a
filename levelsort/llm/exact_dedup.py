"""Exact duplicates by skew-safe combining.

Copies are merged inside each task first (map-side combine), then per (digest, salt), then across the salts
of a digest. Every merge groups by the full normalised content, so equal digests alone never merge two texts.
Only digests with more rows than ``hot_rows`` are salted, with one salt per ``hot_rows`` rows; the table of them that
is broadcast stays under ``BROADCAST_ROWS`` rows: of more, those with the largest groups are salted.

Defined results: null text counts as empty; a null doc_id is a row like any other and loses ties; repeated
rows (same doc_id and text) are all listed, exactly one of them is kept; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelsort.llm.common import SPACE_CLASS, Stage, fresh, largest

BROADCAST_ROWS = 200_000


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_CLASS + "+", " ")


def sha_digest(norm: Column) -> Column:
    return F.unhex(F.sha2(norm, 256))


def copy_classes(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    hot_rows: int = 500,
    digest: Callable[[Column], Column] = sha_digest,
) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = docs.select(F.col(id_col).alias("doc_id"), normalised(F.col(text_col)).alias("norm"))
    ids = Stage(rows.select("doc_id", digest(F.col("norm")).alias("digest"), F.unhex(F.sha2("norm", 256)).alias("sha")), "digests")
    counts = ids.df.groupBy("digest").agg(F.count("*").alias("n")).where(F.col("n") > hot_rows)
    hot = Stage(counts.select("digest", "n", F.ceil(F.col("n") / hot_rows).cast("int").alias("salts")), "hot-digests")
    salts = largest(hot.df, "n", BROADCAST_ROWS).drop("n")

    def salted(df: DataFrame) -> DataFrame:
        with_hot = df.join(salts, "digest", "left")
        salt = F.when(F.col("salts").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("doc_id"), F.col("salts")).cast("int"))
        return with_hot.withColumn("salt", salt)

    keyed = salted(rows.withColumn("digest", digest(F.col("norm"))))
    local = Stage(
        keyed.groupBy("digest", "salt", "norm").agg(F.min("doc_id").alias("low"), F.count("*").alias("n"), F.first("salts").alias("salts"))
        .select("digest", "salt", "low", "n", "salts", F.when(F.col("salts").isNotNull(), F.col("norm")).alias("norm"), F.sha2("norm", 256).alias("text_sha256")),
        "salt-winners",
    )
    cold = local.df.where(F.col("salts").isNull()).select("digest", "salt", "text_sha256", F.col("low").alias("keep_id"), F.col("n").alias("group_size"))
    pieces = local.df.where(F.col("salts").isNotNull())
    merged = pieces.groupBy("digest", "norm").agg(F.min("low").alias("keep_id"), F.sum("n").alias("group_size"))
    warm = pieces.join(merged, ["digest", "norm"]).select("digest", "salt", "text_sha256", "keep_id", "group_size")
    winners = cold.unionByName(warm).withColumn("sha", F.unhex("text_sha256"))
    # a weak digest may hold several contents: the sha of the content that each class was merged under tells them apart
    members = salted(ids.df).join(winners, ["digest", "salt", "sha"])
    alike = members.groupBy("doc_id", "keep_id", "group_size", "text_sha256").agg(F.count("*").alias("times"))
    return alike.select("doc_id", "keep_id", "group_size", F.explode(F.sequence(F.lit(1), F.col("times").cast("int"))).alias("i"), "text_sha256").select(
        "doc_id", "keep_id", "group_size", ((F.col("i") == 1) & F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("kept"), "text_sha256"
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, all columns unchanged; repeated rows leave one."""
    sha_col, id_tmp, sha_tmp = (fresh(docs, n) for n in ("sha", "stay_id", "stay_sha"))
    stay = Stage(copy_classes(docs, id_col, text_col).where("kept").select(F.col("doc_id").alias(id_tmp), F.unhex("text_sha256").alias(sha_tmp)), "stay")
    tagged = docs.withColumn(sha_col, F.unhex(F.sha2(normalised(F.col(text_col)), 256)))
    kept = tagged.join(stay.df, F.col(id_col).eqNullSafe(F.col(id_tmp)) & (F.col(sha_col) == F.col(sha_tmp)), "left_semi")
    n_stay = stay.df.count()
    if kept.select(id_col).count() > n_stay:  # repeated ids with one text: only then one more pass is needed
        kept = kept.dropDuplicates([id_col, sha_col])
    return kept.drop(sha_col)
