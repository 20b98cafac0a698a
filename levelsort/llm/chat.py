"""Chat formatting with cumulative-snapshot collapse (DataFrame functions only).

A logged conversation is often a prefix of a longer one. The prefix of k turns has a rolling hash: the number k with
128 bits of summed turn hashes, each turn hashed with its position, so the hash of the next prefix is this one plus
one turn. Conversations whose whole hash is some longer conversation's prefix hash are anti-joined away; of equal
ones the smallest conv_id stays. What is left is maximal and is rendered.

Sums are taken in two levels - inside blocks of 1024 positions, then over block totals - and rendering gives parts
of at most ``part_turns`` turns, so one endless conversation is never one task's work.

Defined results: repeated rows (same conversation, turn, role and text) are one turn; rows with one turn number are
ordered by role, then text; gaps in turn numbers do not matter; null role or text counts as empty, a null turn comes
first; rows with a null conv_id are left out; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.llm.common import Stage

SPAN = 1024
# Fixed value: how a turn is written.
TURN = "<|{role}|>\n{text}<|end|>\n"


def _numbered(turns: DataFrame) -> DataFrame:
    """Adds pos (1..n in a conversation), by counts of blocks of turn numbers and ranks inside them."""
    block = F.floor(F.coalesce(F.col("turn"), F.lit(-1)) / SPAN)
    rows = turns.withColumn("blk", block)
    sizes = rows.groupBy("conv_id", "blk").agg(F.count("*").alias("c"))
    before = F.coalesce(F.sum("c").over(W.partitionBy("conv_id").orderBy("blk").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    inside = F.row_number().over(W.partitionBy("conv_id", "blk").orderBy(F.col("turn").asc_nulls_first(), "role", "text"))
    return rows.withColumn("inside", inside).join(sizes.select("conv_id", "blk", before.alias("before")), ["conv_id", "blk"]).withColumn("pos", F.col("before") + F.col("inside")).drop("inside", "before", "blk")


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """conv_id, pos, h1..h4 of the prefix that ends there, turn, role, text."""
    rows = _numbered(turns).withColumn("blk", F.floor((F.col("pos") - 1) / SPAN))
    a, b = F.xxhash64(F.lit(1), "pos", "role", "text"), F.xxhash64(F.lit(2), "pos", "role", "text")
    low = 0xFFFFFFFF
    parts = {"h1": a.bitwiseAND(F.lit(low)), "h2": F.shiftrightunsigned(a, 32), "h3": b.bitwiseAND(F.lit(low)), "h4": F.shiftrightunsigned(b, 32)}
    rows = rows.withColumns(parts)
    totals = rows.groupBy("conv_id", "blk").agg(*[F.sum(h).alias(f"t_{h}") for h in parts])
    earlier = W.partitionBy("conv_id").orderBy("blk").rowsBetween(W.unboundedPreceding, -1)
    bases = totals.select("conv_id", "blk", *[F.coalesce(F.sum(f"t_{h}").over(earlier), F.lit(0)).alias(f"b_{h}") for h in parts])
    run = W.partitionBy("conv_id", "blk").orderBy("pos").rowsBetween(W.unboundedPreceding, 0)
    rolled = rows.select("conv_id", "blk", "pos", "turn", "role", "text", *[F.sum(h).over(run).alias(h) for h in parts]).join(bases, ["conv_id", "blk"])
    return rolled.select("conv_id", "pos", "turn", "role", "text", *[(F.col(h) + F.col(f"b_{h}")).alias(h) for h in parts])


def maximal_conversations(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rolled turns with prefix hashes, conv_id and n_turns of the conversations that stay)."""
    clean = turns.select("conv_id", F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).where("conv_id is not null").distinct()
    rolled = Stage(prefix_hashes(clean), "turn-prefixes").df
    key = ["pos", "h1", "h2", "h3", "h4"]
    ends = rolled.groupBy("conv_id").agg(F.max("pos").alias("n_turns"))
    marked = rolled.select("conv_id", *key).join(ends, "conv_id")
    whole = marked.where("pos = n_turns").groupBy(*key).agg(F.min("conv_id").alias("conv_id"))
    inner = marked.where("pos < n_turns").select(*key).distinct()  # one row however many share the prefix
    return rolled, whole.join(inner, key, "left_anti").select("conv_id", F.col("pos").alias("n_turns"))


def render(turns: DataFrame, part_turns: int = SPAN) -> DataFrame:
    """conv_id, part, n_turns (of the conversation), rendered: maximal conversations in parts of bounded length."""
    rolled, stay = maximal_conversations(turns)
    rows = rolled.select("conv_id", "pos", "role", "text").join(stay, "conv_id")
    head, _, rest = TURN.partition("{role}")
    middle, _, tail = rest.partition("{text}")
    line = F.concat(F.lit(head), "role", F.lit(middle), "text", F.lit(tail))
    part = F.floor((F.col("pos") - 1) / part_turns).alias("part")
    grouped = rows.select("conv_id", part, "n_turns", F.struct("pos", line.alias("line")).alias("x")).groupBy("conv_id", "part").agg(F.max("n_turns").alias("n_turns"), F.array_sort(F.collect_list("x")).alias("xs"))
    return grouped.select("conv_id", "part", "n_turns", F.array_join(F.transform("xs", lambda x: x["line"]), "").alias("rendered"))
