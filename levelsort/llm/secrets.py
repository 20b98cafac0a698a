"""Secret scan: fixed patterns plus character Markov models (DataFrame functions only).

Two bigram models over characters - random strings and ordinary identifiers, both trained from labelled samples -
are compared by their log-likelihood ratio on long unbroken tokens; tokens whose ratio is high enough are spans
of kind ``random``. Patterns with names give the spans of the kinds ``assign``, ``access`` and ``hex``.

Positions: the pieces between matches and the matches themselves alternate, so a match starts at the summed
lengths before it. Sums are taken over blocks of 256 matches, so many matches in one text stay cheap.

Defined results: null text is empty; an empty text has no spans; overlapping spans of different kinds are all
reported, a random span only where no pattern span overlaps it; repeated rows get equal results; other columns
are ignored by ``scan`` and kept by ``redact``.
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Kinds in listed order, their patterns and least lengths (of group 2 for assign).
KINDS = ("assign", "access", "hex", "random")
ASSIGN = r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST = {"assign": 8, "access": 16, "hex": 32}

ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-"
TOKEN = r"[A-Za-z0-9+/_-]{20,}"
SYMBOLS = len(ALPHABET) + 1
THRESHOLD = 12.0
_BLOCK = 256

# Parts that ordinary identifiers and long ordinary words are made of.
IDENTIFIER_PARTS = """get set is has to from new old user name list item index count size max min value key map node tree
file path dir read write open close load save data base type class object array string number date time start end
begin init config option param result error message request response client server handler manager factory service
event listener button view model controller page table column row field input output buffer stream thread process
queue stack cache memory token parser lexer builder helper util test mock spec default global local public private
static final abstract interface package module import export function method return update delete insert select
create destroy connect disconnect session cookie header body content length width height color style layout render
draw paint click scroll mouse keyboard press release change version release build deploy docker kubernetes cluster
internal external company example version document information international communication development government
environment understanding responsibility characteristics straightforward interessant gesellschaft verantwortung
entwicklung zusammenarbeit wissenschaft développement gouvernement environnement responsabilite comunicacion
desarrollo universidad responsabilidad informacion naturaleza ation ing tion ment heit keit ung lich schaft ción mente""".split()


def random_samples(n: int = 600) -> list[str]:
    """Labelled random strings: base64, alphanumeric, hexadecimal and lower-case-plus-digit keys from a hash chain."""
    out = []
    for i in range(n):
        digest = b"".join(hashlib.sha256(f"{i}:{j}".encode()).digest() for j in range(2))
        pool = (ALPHABET[:64], ALPHABET[:62], "0123456789abcdef", ALPHABET[:26] + "0123456789")[i % 4]
        out.append("".join(pool[b % len(pool)] for b in digest[: 20 + i % 29]))
    return out


def identifier_samples(n: int = 1200) -> list[str]:
    """Labelled ordinary strings: snake, kebab, camel, path and plain compounds of ordinary parts."""
    parts = [p for p in IDENTIFIER_PARTS if p.isascii()]
    out = []
    for i in range(n):
        pick = [parts[b % len(parts)] for b in hashlib.sha256(f"id{i}".encode()).digest()[: 3 + i % 3]]
        style = i % 6
        if style == 0:
            out.append("_".join(pick))
        elif style == 1:
            out.append("-".join(pick))
        elif style == 2:
            out.append(pick[0] + "".join(p.capitalize() for p in pick[1:]))
        elif style == 3:
            out.append("/".join(pick))
        elif style == 4:
            out.append("_".join(pick).upper() + f"_{i % 100}" * (i % 2))
        else:
            out.append("".join(pick))
    return out


def train(random: list[str], ordinary: list[str], smooth: float = 0.5) -> list[float]:
    """Flat table: at (symbol, previous) the log ratio of the two models' transition probabilities."""

    def transitions(samples: list[str]) -> list[list[float]]:
        n = [[smooth] * SYMBOLS for _ in range(SYMBOLS)]
        for s in samples:
            for a, b in zip(s, s[1:], strict=False):
                n[ALPHABET.find(a) + 1][ALPHABET.find(b) + 1] += 1
        # backed off to the symbol frequencies, so a rare predecessor still has a sensible row
        whole = [sum(n[a][b] for a in range(SYMBOLS)) for b in range(SYMBOLS)]
        total = sum(whole)
        return [[math.log((row[b] + 8 * whole[b] / total) / (sum(row) + 8)) for b in range(SYMBOLS)] for row in n]

    r, o = transitions(random), transitions(ordinary)
    return [round(r[a][b] - o[a][b], 6) for b in range(SYMBOLS) for a in range(SYMBOLS)]


def default_model() -> list[float]:
    return train(random_samples(), identifier_samples())


def ratio(token: str, model: list[float]) -> float:
    """The same ratio for one Python string (tests, threshold choice)."""
    at = [ALPHABET.find(c) + 1 for c in token]
    return sum(model[b * SYMBOLS + a] for a, b in zip(at, at[1:], strict=False))


def _ratio(token: Column, model: Column) -> Column:
    symbol = lambda i: F.instr(F.lit(ALPHABET).substr(F.lit(1), F.lit(len(ALPHABET))), F.substring(token, i, F.lit(1)))
    return F.aggregate(F.sequence(F.lit(2), F.length(token)), F.lit(0.0), lambda acc, i: acc + F.get(model, symbol(i) * SYMBOLS + symbol(i - 1)))


def _before(values: str, i: Column, heads: Column, fold) -> Column:
    """``fold`` of the values before place i: what the blocks before its block come to, and the rest one by one."""
    b = F.floor(i / _BLOCK).cast("int")
    return F.aggregate(F.slice(values, b * _BLOCK + 1, i - b * _BLOCK), F.get(heads, b), fold)


def _heads(values: str, fold) -> Column:
    """Per block of ``values``, ``fold`` of all blocks before it; each value is read once."""
    n = F.floor((F.size(values) + _BLOCK - 1) / _BLOCK).cast("int")
    own = F.transform(F.sequence(F.lit(1), n), lambda b: F.aggregate(F.slice(values, (b - 1) * _BLOCK + 1, F.lit(_BLOCK)), F.lit(0), fold))
    zero = F.array(F.lit(0))
    return F.when(F.size(values) == 0, zero).otherwise(F.aggregate(own, zero, lambda acc, x: F.concat(acc, F.array(fold(F.element_at(acc, -1), x)))))


def _find(df: DataFrame, pattern: str, name: str, least: int, group: int = 0) -> DataFrame:
    """Adds array column ``name`` of struct(start, stop, token) of the matches whose group has ``least`` characters."""
    lit = F.lit(pattern)
    found = df.withColumn("_hit", F.when(F.col("_text").rlike(_quick(pattern)), F.regexp_extract_all("_text", lit, F.lit(0))).otherwise(F.array().cast("array<string>")))
    some = F.size("_hit") > 0
    none = F.array().cast("array<string>")
    found = found.withColumn("_gap", F.when(some, F.split("_text", pattern, -1)).otherwise(none))
    if group:
        found = found.withColumn("_grp", F.when(some, F.regexp_extract_all("_text", lit, F.lit(group))).otherwise(none))
    else:
        found = found.withColumn("_grp", F.col("_hit"))
    found = found.withColumn("_len", F.zip_with("_gap", "_hit", lambda g, h: F.coalesce(F.length(g), F.lit(0)) + F.coalesce(F.length(h), F.lit(0))))
    add = lambda a, x: a + x
    found = found.withColumn("_heads", _heads("_len", add))

    def span(h: Column, i: Column) -> Column:
        start = _before("_len", i, F.col("_heads"), add) + F.length(F.get("_gap", i))
        return F.struct(start.alias("start"), (start + F.length(h)).alias("stop"), F.get("_grp", i).alias("token"))

    spans = F.filter(F.transform("_hit", span), lambda s: F.length(s["token"]) >= least)
    return found.withColumn(name, spans).drop("_hit", "_gap", "_grp", "_len", "_heads")


def _quick(pattern: str) -> str:
    """A pattern that every text with a kept match matches, without captures."""
    return {HEX: "[0-9a-f]{32}", ACCESS: "AKIA[A-Z0-9]{12}"}.get(pattern, pattern)


def spans(docs: DataFrame, text: Column, model: list[float] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """Adds ``_spans``: array of struct(start, rank, stop), by start then kind; and ``_base`` without random ones."""
    table = F.array(*[F.lit(x) for x in (model or default_model())])
    df = docs.withColumn("_text", F.coalesce(text, F.lit("")))
    df = _find(df, ASSIGN, "_assign", LEAST["assign"], 2)
    df = _find(df, ACCESS, "_access", LEAST["access"])
    df = _find(df, HEX, "_hex", LEAST["hex"])
    df = _find(df, TOKEN, "_token", 20)
    ranked = lambda c, k: F.transform(c, lambda s: F.struct(s["start"].alias("start"), F.lit(k).alias("rank"), s["stop"].alias("stop")))
    df = df.withColumn("_base", F.array_sort(F.concat(ranked("_assign", 0), ranked("_access", 1), ranked("_hex", 2))))
    free = lambda s: ~F.exists("_base", lambda b: (b["start"] < s["stop"]) & (s["start"] < b["stop"]))
    df = df.withColumn("_token", F.filter("_token", free))
    df = df.withColumn("_token", F.when(F.size("_token") > 0, F.filter("_token", lambda s: _ratio(s["token"], table) >= threshold)).otherwise(F.col("_token")))
    return df.withColumn("_spans", F.array_sort(F.concat("_base", ranked("_token", 3))))


def _joined(c: str) -> Column:
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(c, lambda s: F.concat_ws(":", F.get(kinds, s["rank"]), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: list[float] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, n_random, base_sha256, spans."""
    found = spans(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), F.col("text"), model, threshold)
    size = lambda c: F.size(c).cast("long")
    return found.select(
        "doc_id", size("_assign").alias("n_assign"), size("_access").alias("n_access"), size("_hex").alias("n_hex"), size("_token").alias("n_random"),
        F.sha2(_joined("_base"), 256).alias("base_sha256"), _joined("_spans").alias("spans"),
    )


def redact(docs: DataFrame, text_col: str = "text", mark: str = "[SECRET]", model: list[float] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` with every span replaced by ``mark``; overlapping spans become one mark; other columns unchanged."""
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])  # under one name: whatever the columns are called
    found = spans(docs.select(whole.alias("_row"), F.col(text_col).alias("_given")), F.col("_given"), model, threshold)
    later = lambda a, x: F.greatest(a, x)
    found = found.withColumn("_stops", F.transform("_spans", lambda s: s["stop"])).withColumn("_heads", _heads("_stops", later))

    def piece(s: Column, i: Column) -> Column:
        at = _before("_stops", i, F.col("_heads"), later)
        return F.when(s["start"] >= at, F.concat(F.substring("_text", at + 1, s["start"] - at), F.lit(mark))).otherwise(F.lit(""))

    tail = F.expr("substring(_text, array_max(_stops) + 1)")
    clean = F.when(F.size("_spans") == 0, F.col("_given")).otherwise(F.concat(F.array_join(F.transform("_spans", piece), ""), tail))
    return found.select(*[(clean if c == text_col else F.col("_row")[c]).alias(c) for c in docs.columns])
