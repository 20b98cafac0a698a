"""Toxicity by a weighted finite-state pattern grammar.

Five transducers read the classes of a clause's words and write marks: *insult* (a word of abuse), *threat* (a verb of
harm with a target behind it, surer behind a modal), *target* (somebody is addressed or named), *negation* (open
for a few words) and *reported speech* (open until the clause ends). They are composed - their product machine is
built once, and an arc carries the channel and the weight that its marks come to - so what is scored is the matched
clause, not the word: an insult is worth less when negated or reported, more when aimed at somebody, and a verb of harm
is a threat only with its target. A lexicon transducer maps words, and word stems, to classes and weights. A document's
score is a logistic function of what its clauses wrote to the channels.

Learned from labelled rows: words and stems of the insult class, by log odds of document counts, beside a short list of
English ones; and the weights of the channels, by logistic regression with a prior. Weights are never negative, a
reported insult never outweighs a plain one, nor a negated one a reported one, a threat is worth no less than an insult,
and a channel that the labelled rows do not show keeps its prior weight otherwise. At most ``max_toxic`` and ``max_clean`` labelled documents (smallest hash first) are
used; their words are counted by Spark, and the driver gets candidate words and a few numbers per document, no texts.
Rows with crc32(doc_id as text) mod 5 = 0 are held out. Scores use the text alone.

Defined results: null or empty text scores as a text without matches; null doc_id is never a training row; a
document with several labels is toxic if any says so; null labels are skipped; without labels of both kinds the
built-in words and prior weights are used; repeated rows get equal scores; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelsort.llm.common import Stage, lean

MAX_TOXIC, MAX_CLEAN = 3000, 6000
# Seed words of each class.
INSULTS = "idiot moron stupid loser scum trash worthless pathetic disgusting clown imbecile vermin filth dumb".split()
THREATS = "kill hurt destroy murder stab shoot beat burn attack hang".split()
TARGETS = "you your yours yourself youre they them he she him her all everyone du dich ihr euch sie tu te toi vous ils tú usted ustedes vosotros ellos".split()
NEGATIONS = "not no never neither nor cannot dont doesnt isnt arent wasnt wont nicht kein keine nie ne pas jamais nunca".split()
REPORTS = "said says say told wrote writes claimed claims quoted reported according called sagte schrieb dit écrit dijo escribió".split()
MODALS = "will shall gonna going must should ll werde wird werden vais va vont voy vamos".split()

OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT, MODAL = range(7)
CLASSES = 7
CHANNELS = ("plain", "targeted", "negated", "reported", "threat")
PLAIN, TARGETED, NEGATED, REPORTED, THREATENED = range(5)
_TOKENS = re.compile(r"[^\W_]+|[.!?;\n]")
_ENDS = frozenset(".!?;\n")
_STEM = range(3, 9)
MEMO = 400_000
#: A led threat is worth two seed insults, a bare one half of one.
THREAT_WEIGHT, BARE = 8.0, 0.25


class Transducer:
    """States 0 (start) to size - 1; ``step(state, cls)`` gives (next state, marks written); ``final(state)`` marks at the end."""

    def __init__(self, size: int, step, final=lambda s: frozenset()):
        self.size, self.step, self.final = size, step, final


NOTHING: frozenset = frozenset()


def insult_machine() -> Transducer:
    return Transducer(1, lambda s, c: (0, frozenset({"insult"}) if c == INSULT else NOTHING))


def threat_machine(lead: int = 4, reach: int = 3) -> Transducer:
    """A verb of harm and a target up to ``reach`` words behind it; ``sure`` with a modal up to ``lead`` words before it.

    States: 0; 1..lead, a modal so many words open; then ``reach`` after a bare verb, and ``reach`` after a led one.
    """

    def step(s: int, c: int):
        led, bare, sure = 0 < s <= lead, lead < s <= lead + reach, s > lead + reach
        if c == THREAT:
            return lead + reach * (2 if led or sure else 1), NOTHING
        if c == TARGET and (bare or sure):
            return 0, frozenset({"threat", "sure"}) if sure else frozenset({"threat"})
        if c == MODAL and not (bare or sure):
            return lead, NOTHING
        return (0 if s in (0, 1, lead + 1, lead + reach + 1) else s - 1), NOTHING

    return Transducer(1 + lead + 2 * reach, step)


def target_machine() -> Transducer:
    return Transducer(2, lambda s, c: (1 if c == TARGET else s, NOTHING), lambda s: frozenset({"targeted"}) if s else NOTHING)


def negation_machine(reach: int = 3) -> Transducer:
    """Marks the ``reach`` words after a negation."""
    return Transducer(reach + 1, lambda s, c: (reach if c == NEGATION else max(0, s - 1), frozenset({"negated"}) if s else NOTHING))


def report_machine() -> Transducer:
    """Marks what follows a verb of speech, until the clause ends."""
    return Transducer(2, lambda s, c: (1 if c == REPORT else s, frozenset({"reported"}) if s else NOTHING))


def channel_of(marks: frozenset) -> tuple[int, float] | None:
    """What the marks of one arc come to: a channel and a factor of the word's weight."""
    if not marks & {"insult", "threat"}:
        return None
    if "negated" in marks:
        return NEGATED, 1.0
    if "reported" in marks:
        return REPORTED, 1.0
    return (PLAIN, 1.0) if "insult" in marks else (THREATENED, 1.0 if "sure" in marks else BARE)


class Grammar:
    """The composition of the five machines: only states that can be reached, arcs with channel and factor."""

    def __init__(self):
        self.parts = (insult_machine(), threat_machine(), target_machine(), negation_machine(), report_machine())
        number = {(0,) * len(self.parts): 0}
        todo = list(number)
        self.next: list[list[int]] = []
        self.emits: list[list[tuple[int, float] | None]] = []
        self.targeted: list[bool] = []
        for own in todo:
            follow, emits = [], []
            for c in range(CLASSES):
                steps = [m.step(x, c) for m, x in zip(self.parts, own, strict=True)]
                to = tuple(x for x, _ in steps)
                if to not in number:
                    number[to] = len(number)
                    todo.append(to)
                follow.append(number[to])
                emits.append(channel_of(frozenset().union(*(marks for _, marks in steps))))
            self.next.append(follow)
            self.emits.append(emits)
            self.targeted.append("targeted" in frozenset().union(*(m.final(x) for m, x in zip(self.parts, own, strict=True))))

    def run(self, clause: list[tuple[int, float]]) -> list[float] | None:
        """Channel weights of one clause, None without a match. The final mark says whether its insults were aimed."""
        state, found, out = 0, False, [0.0] * len(CHANNELS)
        for cls, weight in clause:
            if (emit := self.emits[state][cls]) is not None:
                found = True
                out[emit[0]] += emit[1] * (weight or THREAT_WEIGHT)
            state = self.next[state][cls]
        if not found:
            return None
        if self.targeted[state]:
            out[TARGETED] = out[PLAIN]
        return out


class Lexicon(dict):
    """word -> (class, weight) or None; stems are tried longest first; bounded memo."""

    def __init__(self, words: dict[str, float], stems: dict[str, float]):
        super().__init__()
        self.fixed: dict[str, tuple[int, float] | None] = {}
        for cls, names, weight in ((MODAL, MODALS, 0.0), (TARGET, TARGETS, 0.0), (NEGATION, NEGATIONS, 0.0), (REPORT, REPORTS, 0.0), (THREAT, THREATS, 0.0), (INSULT, INSULTS, 4.0)):
            self.fixed.update((w, (cls, weight)) for w in names)
        self.fixed.update((w, (INSULT, x)) for w, x in words.items())
        self.fixed.update((w, w) for w in _ENDS)
        self.stems = stems
        self.lengths = sorted({len(s) for s in stems}, reverse=True)

    def __missing__(self, word: str):
        if len(self) > MEMO:
            self.clear()
        value = self.fixed.get(word)
        if value is None:
            for n in self.lengths:
                if len(word) >= n and (x := self.stems.get(word[:n])) is not None:
                    value = (INSULT, x)
                    break
        self[word] = value
        return value


def channels(text: str | None, lexicon: Lexicon, grammar: Grammar) -> list[float]:
    """Summed channel weights of the matched clauses, and how many clauses matched."""
    total, matched = [0.0] * len(CHANNELS), 0
    clause: list[tuple[int, float]] = []
    hot = False
    for x in [*map(lexicon.__getitem__, _TOKENS.findall((text or "").lower())), "."]:
        if x is None:
            clause.append((OTHER, 0.0))
        elif type(x) is str:
            if hot and (out := grammar.run(clause)):
                matched += 1
                total = [a + b for a, b in zip(total, out, strict=True)]
            clause, hot = [], False
        else:
            clause.append(x)
            hot = hot or x[0] == INSULT or x[0] == THREAT
    return [*total, float(matched)]


def _features(rows: list[list[float]]) -> np.ndarray:
    """Of each channel log(1 + weight); aimed insults count as plain ones and, once more, as aimed."""
    return np.log1p(np.array(rows, float).reshape(-1, len(CHANNELS) + 1)[:, : len(CHANNELS)])


#: Prior weights of the channels and the bias, and how many labelled documents' worth of curvature they have.
PRIOR, PRIOR_BIAS, PRIOR_STRENGTH = (2.0, 0.4, 0.2, 0.5, 2.6), -3.5, 0.5


class Model:
    def __init__(self, words: dict[str, float], stems: dict[str, float], weights: list[float], bias: float):
        self.words, self.stems, self.weights, self.bias = words, stems, weights, bias

    def scores(self, rows: list[list[float]]) -> np.ndarray:
        return 1 / (1 + np.exp(-(_features(rows) @ np.array(self.weights) + self.bias)))


def _document_words(text: str) -> set[str]:
    return {w for w in _TOKENS.findall(text.lower()) if len(w) > 2}


def choose_words(counts: dict[str, tuple[int, int, int]], n1: int, n0: int, least: int) -> tuple[dict[str, float], dict[str, float]]:
    """Words, and stems (written with a star) shared by several words, that mark toxic documents.

    ``counts``: feature -> toxic documents, clean documents, toxic words under a stem. Values are log odds.
    """
    odds = {}
    for f, (a, b, _) in counts.items():
        if a >= least:
            x = math.log((a + 0.5) / (n1 + 1)) - math.log((b + 0.5) / (n0 + 1))
            if x >= 2.5 and (b <= a or x >= 3):
                odds[f] = min(x, 6.0)
    stems: dict[str, float] = {}
    for f in sorted((f for f in odds if f[-1] == "*"), key=lambda f: (len(f), f)):
        if counts[f][2] < 4 or counts[f][0] < 2 * least or any(f.startswith(s) for s in stems):
            continue
        # a longer stem (or word) that is as frequent, or much surer, says it better
        longer = [g for g in odds if g.startswith(f[:-1]) and g != f and (len(g) > len(f) or g[-1] != "*")]
        if not any(counts[g][0] >= 0.95 * counts[f][0] or (odds[g] >= odds[f] + 1 and counts[g][0] >= 0.15 * counts[f][0]) for g in longer if g[-1] == "*" or odds[g] >= odds[f] + 1):
            stems[f[:-1]] = odds[f]
    words = {f: x for f, x in odds.items() if f[-1] != "*" and not any(f.startswith(s) and x < y + 1 for s, y in stems.items())}
    return words, stems


def fit_channels(rows: list[list[float]], y: list[int]) -> tuple[list[float], float]:
    """Weights and bias: Newton steps towards the labels from the prior, kept within the order of the channels."""
    x = np.hstack([_features(rows), np.ones((len(rows), 1))])
    t, prior = np.array(y, float), np.array([*PRIOR, PRIOR_BIAS])
    w, hold = prior.copy(), np.diag([PRIOR_STRENGTH] * len(PRIOR) + [0.05])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -40, 40)))
        step = np.linalg.solve((x.T * (p * (1 - p))) @ x + hold, x.T @ (t - p) - hold @ (w - prior))
        before = w.copy()
        w = w + step * min(1.0, 2 / (1e-9 + np.abs(step).max()))
        w[:-1] = np.maximum(w[:-1], 0.0)
        w[THREATENED] = max(w[THREATENED], w[PLAIN])
        w[REPORTED] = min(w[REPORTED], w[PLAIN])
        w[NEGATED] = min(w[NEGATED], w[REPORTED])
        if np.abs(w - before).max() < 1e-6:
            break
    return [float(v) for v in w[:-1]], float(w[-1])


def held_out(doc_id):
    return F.coalesce(F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0, F.lit(False))


def _word_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(y, sketch, words) per document; documents with one sketch say the same."""
    for b in batches:
        for at in range(0, b.num_rows, 256):
            part = b.slice(at, 256)
            y = part.column("y").to_pylist()
            words = [sorted(_document_words(t)) for t in part.column("text").to_pylist()]
            sketch = [",".join(str(h) for h in (v, *sorted(zlib.crc32(w.encode("utf-8", "surrogatepass")) for w in ws)[:3])) for v, ws in zip(y, words, strict=True)]
            yield pa.RecordBatch.from_arrays([part.column("_id"), pa.array(y, pa.int32()), pa.array(sketch, pa.string()), pa.array(words, pa.list_(pa.string()))], ["_id", "y", "sketch", "words"])


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_toxic: int = MAX_TOXIC, max_clean: int = MAX_CLEAN, least: int = 3) -> Model:
    once = labels.select(F.col(id_col).cast("long").alias("_id"), F.col(label_col).cast("int").alias("y")).where("_id is not null and y is not null").groupBy("_id").agg(F.max("y").alias("y")).where(~held_out(F.col("_id")))
    order = (F.xxhash64("_id"), F.col("_id"))
    picked = once.where("y = 1").orderBy(*order).limit(max_toxic).unionByName(once.where("y <> 1").withColumn("y", F.lit(0)).orderBy(*order).limit(max_clean))
    chosen = Stage(picked, "labelled")
    texts = Stage(docs.select(F.col(id_col).cast("long").alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(chosen.df), "_id"), "labelled-texts")  # at most max_toxic + max_clean ids
    sets = texts.df.select("_id", "text", "y").mapInArrow(_word_rows, "_id long, y int, sketch string, words array<string>")
    sets = Stage(sets.groupBy("y", "sketch").agg(F.min_by("words", "_id").alias("words")), "labelled-words")  # copies of one document say nothing new
    n = {r["y"]: r["n"] for r in sets.df.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if not n.get(0) or not n.get(1):
        return Model({}, {}, list(PRIOR), PRIOR_BIAS)
    least = max(least, math.ceil(0.006 * n[1]))
    stems = F.flatten(F.array(*[F.transform(F.filter("words", lambda w, k=k: F.length(w) > k), lambda w, k=k: F.concat(F.left(w, F.lit(k)), F.lit("*"))) for k in _STEM]))
    features = sets.df.select("y", F.explode(F.concat("words", F.array_distinct(stems))).alias("f"))
    counted = features.groupBy("f").agg(F.sum("y").alias("a"), F.sum(1 - F.col("y")).alias("b"))
    wanted = Stage(counted.where((F.col("a") >= least) & (F.col("b") * n[1] * 4 < F.col("a") * n[0] + 4 * n[0])), "marked-words")  # others have too low odds
    toxic_words = sets.df.where("y = 1").select(F.explode("words").alias("w")).distinct()
    under = toxic_words.select(F.explode(F.array(*[F.when(F.length("w") > k, F.concat(F.left("w", F.lit(k)), F.lit("*"))) for k in _STEM])).alias("f")).where("f is not null").groupBy("f").agg(F.count("*").alias("kinds"))
    rows = wanted.df.join(under, "f", "left").select("f", "a", "b", F.coalesce("kinds", F.lit(0)).alias("kinds")).collect()
    words, found = choose_words({r["f"]: (r["a"], r["b"], r["kinds"]) for r in rows}, n[1], n[0], least)
    lexicon_only = Model(words, found, list(PRIOR), PRIOR_BIAS)
    scored = texts.df.select("_id", "y", F.col("text").alias("text")).mapInArrow(_channel_rows(lexicon_only), "y int, c array<double>").collect()
    weights, bias = fit_channels([r["c"] for r in scored], [r["y"] for r in scored])
    for s in (chosen, texts, sets, wanted):
        s.drop()
    return Model(words, found, weights, bias)


def _channel_rows(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon, grammar = Lexicon(model.words, model.stems), Grammar()
        for b in batches:
            rows = [channels(t, lexicon, grammar) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("y"), pa.array(rows, pa.list_(pa.float64()))], ["y", "c"])

    return run


def _scorer(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon, grammar = Lexicon(model.words, model.stems), Grammar()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                rows = [channels(t, lexicon, grammar) for t in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(model.scores(rows)), pa.array([int(r[-1]) for r in rows], pa.int64())], ["doc_id", "score", "clauses"])

    return run


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted, clauses (matched)."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    out = texts.mapInArrow(_scorer(model), "doc_id long, score double, clauses long")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "clauses")


def drop_toxic(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """Rows scored under 0.5, all columns unchanged."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon, grammar = Lexicon(model.words, model.stems), Grammar()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                keep = model.scores([channels(t, lexicon, grammar) for t in part.column(text_col).to_pylist()]) < 0.5
                yield part.filter(pa.array(keep))

    return docs.mapInArrow(lean(run), docs.schema).select(*names)
