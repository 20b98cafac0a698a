"""String sets: DataFrames (src_id BIGINT, pos INT, s STRING) made from the given tables, with their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

NEWLINE = "\n"
#: Letters of generated strings.
LETTERS = "abcdefghijklmnopqrstuvwxyz"


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def pieces(df: DataFrame, id_col: str, text: str | Column, cut: str = NEWLINE, trim: bool = False) -> DataFrame:
    """Non-empty pieces of a text column between matches of ``cut``, with their position."""
    out = df.select(F.col(id_col).cast("bigint").alias("src_id"), F.posexplode(F.split(text, cut)).alias("pos", "s"))
    if trim:
        out = out.withColumn("s", F.trim("s"))
    return out.where(F.col("s") != "")


def whole(df: DataFrame, id_col: str, key: str | Column, pos: str | None = None) -> DataFrame:
    return df.select(F.col(id_col).cast("bigint").alias("src_id"), (F.col(pos) if pos else F.lit(0)).cast("int").alias("pos"), (F.col(key) if isinstance(key, str) else key).alias("s"))


def read_lines(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """Lines of text, CSV or JSON files; the locator is the scan's partition and the line's place in it.

    Both are non-negative and the same in every reading (and in repeated tasks) of the same files under one split size.
    """
    df = spark.read.format(fmt).load(path)
    line = F.col("value") if fmt == "text" else F.to_json(F.struct(*df.columns))
    at = df.select(F.monotonically_increasing_id().alias("at"), line.alias("s"))
    return at.select(F.shiftrightunsigned("at", 33).cast("bigint").alias("src_id"), F.col("at").bitwiseAND(F.lit((1 << 33) - 1)).cast("int").alias("pos"), "s")


def as_key(df: DataFrame, cols: list[str], sep: str = "|") -> Column:
    """Order-preserving text of several columns: integers shifted above zero and padded, timestamps to microseconds."""
    kinds = dict(df.dtypes)
    parts = []
    for c in cols:
        if kinds[c] in ("int", "bigint", "smallint", "tinyint"):
            parts.append(F.lpad((F.col(c).cast("decimal(20,0)") + F.lit(str(1 << 63)).cast("decimal(20,0)")).cast("decimal(20,0)").cast("string"), 20, "0"))
        elif kinds[c].startswith("timestamp"):
            parts.append(F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS"))
        else:
            parts.append(F.col(c).cast("string"))
    return F.concat_ws(sep, *parts)


#: Digits that tell generated strings apart, at least; multipliers that shuffle them (primes, so one divides n or is coprime).
DN_DIGITS = 7
SHUFFLES = (7919, 7927, 7933)


def _digits(n: int, base: int) -> int:
    digits = DN_DIGITS
    while base**digits < n:
        digits += 1
    return digits


def dn_strings(index: DataFrame, n: int, length: int, ratio: float, base: int = 26) -> DataFrame:
    """n unique strings of one length whose distinguishing prefixes take about ``ratio`` of it.

    ``index``: column i (0..n-1). A common run, then base-26 digits of a shuffled i, then hash filler.
    """
    digits = _digits(n, base)
    q = min(length, max(digits, round(ratio * length)))
    if digits > length:
        raise ValueError(f"{n} strings of {length} characters cannot all differ")
    factor = next((m for m in SHUFFLES if n % m), 1)  # coprime to n: the shuffle is a bijection
    shuffled = F.pmod(F.col("i") * factor + 13, F.lit(n))
    code = F.concat(*[F.substr(F.lit(LETTERS), (F.pmod(F.floor(shuffled / F.lit(base**k)), F.lit(base)) + 1).cast("int"), F.lit(1)) for k in reversed(range(digits))])
    filler = F.substring(F.repeat(F.md5(F.col("i").cast("string")), length // 32 + 1), 1, length - q)
    return index.select(F.col("i").cast("bigint").alias("src_id"), F.lit(0).alias("pos"), F.concat(F.lit("a" * (q - digits)), code, filler).alias("s"))


def dn_sql(index_sql: str, n_sql: str, length: int, ratio: float, base: int = 26) -> str:
    """``index_sql``: rows i; ``n_sql``: their number, at most base to the power of ``DN_DIGITS``."""
    q = max(DN_DIGITS, round(ratio * length))
    factor = "CASE " + " ".join(f"WHEN n % {m} <> 0 THEN {m}" for m in SHUFFLES) + " ELSE 1 END"
    code = " || ".join(f"substring('{LETTERS}', CAST(x // {base**k} % {base} + 1 AS INT), 1)" for k in reversed(range(DN_DIGITS)))
    return f"""SELECT CAST(i AS BIGINT) AS src_id, 0 AS pos, repeat('a', {q - DN_DIGITS}) || {code} || left(repeat(md5(CAST(i AS VARCHAR)), {length // 32 + 1}), {length - q}) AS s
        FROM (SELECT i, (i * ({factor}) + 13) % n AS x FROM ({index_sql}) CROSS JOIN (SELECT {n_sql} AS n))"""


def _lines_sql(table: str, key: str, text: str, trim: bool = False) -> str:
    s = "trim(s)" if trim else "s"
    return f"""SELECT CAST(src_id AS BIGINT) AS src_id, CAST(p - 1 AS INT) AS pos, {s} AS s FROM (SELECT {key} AS src_id, unnest(string_split({text}, chr(10))) AS s,
      generate_subscripts(string_split({text}, chr(10)), 1) AS p FROM {table}) WHERE {s} <> ''"""


#: Length of generated strings, and which share of the orders each size of a set has: n grows with the table.
DN_LENGTH = 500
DN_SIZES = {"": 1, "_tenth": 10, "_hundredth": 100}


def _dn(ratio: float, share: int) -> tuple[Callable, str]:
    """One string per order (or per ``share`` orders, by dense key): order keys count from 0 or 1 without gaps."""

    def make(spark: SparkSession, sf_dir: str) -> DataFrame:
        keys = load(spark, sf_dir, "orders", ["o_orderkey"])
        low, n_all = keys.agg(F.min("o_orderkey"), F.count("*")).first()
        n = -(-n_all // share)
        index = keys.select((F.col("o_orderkey") - F.lit(low or 0)).alias("i"))
        return dn_strings(index.where(F.col("i") < n) if share > 1 else index, max(1, n), DN_LENGTH, ratio)

    n = f"(SELECT (count(*) + {share - 1}) // {share} FROM orders)"
    index = "SELECT o_orderkey - (SELECT min(o_orderkey) FROM orders) AS i FROM orders"
    return make, dn_sql(f"SELECT i FROM ({index}) WHERE i < {n}", n, DN_LENGTH, ratio)


#: name -> (spark function, DuckDB statement)
SETS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "lines": (lambda s, d: pieces(load(s, d, "documents", ["doc_id", "text"]), "doc_id", "text"), _lines_sql("documents", "doc_id", "text")),
    "texts": (lambda s, d: whole(load(s, d, "documents", ["doc_id", "text"]), "doc_id", "text"), "SELECT doc_id AS src_id, 0 AS pos, text AS s FROM documents"),
    "markup": (lambda s, d: pieces(load(s, d, "pages", ["page_id", "html"]), "page_id", F.regexp_replace("html", ">", ">\n"), trim=True), _lines_sql("pages", "page_id", "replace(html, '>', '>' || chr(10))", True)),
    "plain": (lambda s, d: pieces(load(s, d, "pages", ["page_id", "html"]), "page_id", F.regexp_replace("html", "<[^>]*>", "\n"), trim=True), _lines_sql("pages", "page_id", "regexp_replace(html, '<[^>]*>', chr(10), 'g')", True)),
    "page_lines": (lambda s, d: pieces(load(s, d, "pages", ["page_id", "html"]), "page_id", "html"), _lines_sql("pages", "page_id", "html")),
    "url": (lambda s, d: whole(load(s, d, "pages", ["page_id", "url"]), "page_id", "url"), "SELECT page_id AS src_id, 0 AS pos, url AS s FROM pages"),
    "conv": (lambda s, d: whole(load(s, d, "conversations", ["conv_id", "turn", "text"]), "conv_id", "text", "turn"), "SELECT conv_id AS src_id, CAST(turn AS INT) AS pos, text AS s FROM conversations"),
    "customer": (lambda s, d: whole(load(s, d, "customer", ["c_custkey", "c_name"]), "c_custkey", "c_name"), "SELECT c_custkey AS src_id, 0 AS pos, c_name AS s FROM customer"),
    "part": (lambda s, d: whole(load(s, d, "part", ["p_partkey", "p_name"]), "p_partkey", "p_name"), "SELECT p_partkey AS src_id, 0 AS pos, p_name AS s FROM part"),
    "props": (lambda s, d: whole(load(s, d, "events", ["event_id", "props"]), "event_id", "props"), "SELECT event_id AS src_id, 0 AS pos, props AS s FROM events"),
    "lineitem": (lambda s, d: whole(load(s, d, "lineitem", ["l_orderkey", "l_linenumber"]), "l_orderkey", F.lpad(F.col("l_orderkey").cast("string"), 12, "0"), "l_linenumber"), "SELECT l_orderkey AS src_id, l_linenumber AS pos, lpad(CAST(l_orderkey AS VARCHAR), 12, '0') AS s FROM lineitem"),
    **{f"dn{round(100 * r):03d}{size}": _dn(r, share) for r in (0, 0.25, 0.5, 0.75, 1) for size, share in DN_SIZES.items() if r == 0.5 or not size},
}


def string_set(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return SETS[name][0](spark, sf_dir)
