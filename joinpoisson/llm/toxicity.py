"""Toxicity by noisy-channel deobfuscation.

A token that may be disguised (a figure or symbol that can replace a letter, a letter three times or more in a row)
is read as a lattice: each character stands for itself or for the letters that it may replace, a run may stand for
one or two letters. Letters that stand apart form one lattice, in which a word may end between any two. The Viterbi path of least cost under a character trigram model and the channel's
costs is the restored token. Restored texts are scored by the words, and by the beginnings of words, that mark toxic
labels.

Learning: the character model counts the words of all documents. Of the labels outside the held-out fifth, at most
PER_CLASS rows of each class, those with the least hash of doc_id, give the word counts and the logistic fit; every
document is scored.
Only the text enters a score. Cases: a null or empty text scores by the fit's intercept; repeated rows score alike;
labels that name no document, null labels and repeated labels take no part beyond their first; with no labels of
either class every score is 0; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.llm.common import col, cut, hash_sample

PER_CLASS, REMEMBERED = 8000, 100_000
FOLDS, HELD_OUT = 5, 0
#: Characters and the letters that they commonly replace.
LEET = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "€": "e", "£": "l"}
PREFIXES = (4, 5, 6, 7, 8)
EVIDENCE = ("marked", "top", "second", "total", "words")
EDGE = ".,;:?\"'()[]{}<>«»¿¡…*_~`-%#&=^/\\"
COST_SWAP, COST_KEEP_ODD, COST_FOLD = 0.7, 6.0, 0.5
_ODD = re.compile(r"[0134579@$!|+€£8(]")
_RUN = re.compile(r"(.)\1\1")
_SPACED = re.compile(r"(?<![^\s\"'(\[«¿¡])(?:[^\W_]|[@$!|+(€£])(?:[\s.\-_*]+(?:[^\W_]|[@$!|+(€£])(?![^\s.\-_*,;:?!\"')\]»…]))+")
_BETWEEN = re.compile(r"[\s.\-_*]+")


@dataclass
class CharModel:
    """Add-a-little trigrams over letters, ^ and $ at the ends."""

    three: dict[str, float] = field(default_factory=dict)
    two: dict[str, float] = field(default_factory=dict)
    letters: int = 30

    def cost(self, context: str, c: str) -> float:
        return -math.log((self.three.get(context + c, 0.0) + 0.02) / (self.two.get(context, 0.0) + 0.02 * self.letters))


def character_model(trigrams: dict[str, float]) -> CharModel:
    two: Counter = Counter()
    for g, n in trigrams.items():
        two[g[:2]] += n
    return CharModel(dict(trigrams), dict(two), max(30, len({g[2] for g in trigrams})))


def lattice(token: str) -> list[list[tuple[str, float]]]:
    """For each run of one character the strings that it may stand for, with the channel's cost."""
    out = []
    for m in re.finditer(r"(.)\1*", token, re.S):
        c, n = m[1], len(m[0])
        choices = []
        for x, cost in [(c, 0.0 if c.isalpha() else COST_KEEP_ODD)] + [(y, COST_SWAP) for y in LEET.get(c, "")]:
            lengths = {n: 0.0} if n < 3 else {1: COST_FOLD, 2: COST_FOLD}
            choices += [(x * k, cost * k + extra) for k, extra in lengths.items()]
        out.append(choices)
    return out


def decode(token: str, model: CharModel) -> str:
    """The string of least cost through the token's lattice."""
    return segmented(lattice(token), model, False)[0]


def decode_spaced(letters: str, model: CharModel) -> list[str]:
    """The words of least cost through the lattice of letters that stood apart: between two of them a word may end."""
    steps = []
    for m in re.finditer(r"(.)\1*", letters, re.S):
        steps += [lattice(m[1])[0] + ([("", COST_FOLD)] if k and len(m[0]) > 2 else []) for k in range(len(m[0]))]
    return segmented(steps, model, True)


def segmented(steps: list[list[tuple[str, float]]], model: CharModel, spaces: bool) -> list[str]:
    best = {"^^": (0.0, "")}
    for k, choices in enumerate(steps):
        if spaces and k:
            best["^^"] = min((cost + model.cost(c, "$"), text + " ") for c, (cost, text) in best.items())
        step: dict[str, tuple[float, str]] = {}
        for context, (cost, text) in best.items():
            for x, extra in choices:
                c, total = context, cost + extra
                for ch in x:
                    total += model.cost(c, ch)
                    c = c[1] + ch
                if c not in step or (total, text + x) < step[c]:
                    step[c] = (total, text + x)
        best = step
    text = min((cost + model.cost(c, "$"), text) for c, (cost, text) in best.items())[1]
    return text.split(" ") if spaces else [text]


class Restorer:
    """Tokens of a text, disguised ones restored. Remembers what tokens became, up to a bound."""

    def __init__(self, model: CharModel):
        self.model, self.seen = model, {}

    def restore(self, token: str) -> str:
        core = token.strip(EDGE).rstrip("!")
        if _ODD.search(core) or _RUN.search(core):
            return decode(core, self.model)
        return core

    def tokens(self, text: str | None) -> set[str]:
        low = (text or "").lower()
        raw = set(low.split())
        joined = {_BETWEEN.sub("", m[0]) for m in _SPACED.finditer(low)} if _maybe_spaced(raw) else set()
        out, seen = set(), self.seen
        for t in raw:
            if (r := seen.get(t)) is None:
                if len(seen) >= REMEMBERED:
                    seen.clear()
                r = self.restore(t)
                if len(t) <= 64:
                    seen[t] = r
            out.add(r)
            if t.isdigit():  # a number may be meant as well
                out.add(t)
        for j in joined:
            out.update(decode_spaced(j, self.model))
        out.discard("")
        return out


def _maybe_spaced(raw: set[str]) -> bool:
    return any(len(t) == 1 or (len(t) > 2 and t[1] in ".-_*") for t in raw)


def features(word: str) -> list[str]:
    return [word, *("^" + word[:k] for k in PREFIXES if len(word) > k)]


@dataclass
class ToxicityModel:
    chars: CharModel
    weight: dict[str, float]
    fit: tuple[float, ...] = (-30.0, *[0.0] * len(EVIDENCE))

    def evidence(self, restorer: Restorer, text: str | None, known: dict[str, float]) -> tuple[float, ...]:
        """Whether a word of the text is marked; then the two strongest marks and the logarithms of the sum of all marks and of the number of words, else zeros."""
        top, second, total = 0.0, 0.0, 0.0
        weight = self.weight
        words = restorer.tokens(text)
        for w in words:
            if (x := known.get(w)) is None:
                if len(known) >= REMEMBERED:
                    known.clear()
                x = known[w] = max((weight.get(f, 0.0) for f in features(w)), default=0.0)
            if x > 0:
                total += x
                if x > top:
                    top, second = x, top
                elif x > second:
                    second = x
        return (1.0, top, second, math.log1p(total), math.log1p(len(words))) if top else (0.0,) * len(EVIDENCE)

    def score(self, evidence: tuple[float, ...]) -> float:
        z = self.fit[0] + sum(a * b for a, b in zip(self.fit[1:], evidence, strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def held_out(doc_id: str = "doc_id"):
    return F.pmod(F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")), F.lit(FOLDS)) == HELD_OUT


def training_texts(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """toxic, text of the bounded sample, each text once."""
    marked = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out())
    picked = None
    for y in (0, 1):
        some = hash_sample(marked.where(F.col("toxic") == y).select("doc_id", "toxic"), per_class, "doc_id")
        picked = some if picked is None else picked.unionByName(some)
    # At most twice per_class rows of a number each.
    picked = picked.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    return cut(docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("toxic", F.coalesce("text", F.lit("")).alias("text")).groupBy("text").agg(F.max("toxic").alias("toxic")).repartition("text"), "toxic-sample")


def trigrams_of(words: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
    """The trigrams of words between ^^ and $, each as one number of three code points, and how often they stand in all words."""
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    points = np.frombuffer("".join(f"^^{w}$" for w in words).encode("utf-32-le"), np.uint32).astype(np.int64)
    sizes = np.fromiter((len(w) + 3 for w in words), np.int64, len(words))
    last = np.cumsum(sizes)
    inside = np.ones(len(points), bool)
    inside[last - 1] = inside[last - 2] = False  # no trigram goes on into the next word
    at = np.flatnonzero(inside)
    grams, which = np.unique(points[at] << 42 | points[at + 1] << 21 | points[at + 2], return_inverse=True)
    counts = np.zeros(len(grams), np.int64)
    np.add.at(counts, which, np.repeat(np.fromiter(words.values(), np.int64, len(words)), sizes)[at])
    return grams, counts


def _count_trigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: Counter = Counter()  # letters are few, so their triples are

    def add(words: Counter) -> None:
        plain: Counter = Counter()
        for w, n in words.items():
            w = w.strip(EDGE + "!")
            if w.isalpha():
                plain[w] += n
        for g, n in zip(*(x.tolist() for x in trigrams_of(plain)), strict=True):
            total[g] += n
        words.clear()

    words: Counter = Counter()
    for b in batches:
        for text in b.column(0):
            words.update(set(text.as_py().lower().split()))
            if len(words) >= REMEMBERED:
                add(words)
    add(words)
    names = ["".join(chr(g >> shift & 0x1FFFFF) for shift in (42, 21, 0)) for g in total]
    yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(list(total.values()), pa.int64())], names=["g", "n"])


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> ToxicityModel:
    sample = training_texts(docs, labels, per_class)
    by_class = dict(sample.groupBy("toxic").count().collect())
    bad, good = by_class.get(1, 0), by_class.get(0, 0)
    grams = docs.select(F.coalesce("text", F.lit("")).alias("text")).mapInArrow(_count_trigrams, "g string, n long").groupBy("g").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "g").collect()
    chars = character_model({r["g"]: float(r["n"]) for r in grams})
    if not bad or not good:
        return ToxicityModel(chars, {})
    least = max(3, math.ceil(0.004 * bad))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(chars)
        seen: tuple[Counter, Counter] = (Counter(), Counter())
        for b in batches:
            for y, text in zip(b.column("toxic").to_pylist(), b.column("text").to_pylist(), strict=True):
                seen[y].update({f for w in restorer.tokens(text) for f in features(w)})
        names = list(seen[0].keys() | seen[1].keys())
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), *[pa.array([s[f] for f in names], pa.int64()) for s in seen]], names=["f", "good", "bad"])

    counts = sample.mapInArrow(count, "f string, good long, bad long").groupBy("f").agg(F.sum("good").alias("good"), F.sum("bad").alias("bad"))
    odds = F.log((F.col("bad") + 0.5) / (bad + 1.0)) - F.log((F.col("good") + 0.5) / (good + 1.0))
    top = counts.where(F.col("bad") >= least).withColumn("w", odds).where("w > 1.5").collect()  # no more than the words of the bounded sample
    model = ToxicityModel(chars, {r["f"]: float(r["w"]) for r in top})

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer, known = Restorer(chars), {}
        for b in batches:
            rows = [(float(y), *model.evidence(restorer, t, known)) for y, t in zip(b.column("toxic").to_pylist(), b.column("text").to_pylist(), strict=True)]
            columns = list(zip(*rows, strict=True)) or [()] * (1 + len(EVIDENCE))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.float64()) for c in columns], names=["y", *EVIDENCE])

    seen = sample.mapInArrow(measure, ", ".join(f"{c} double" for c in ("y", *EVIDENCE))).collect()  # at most twice per_class rows
    points = np.array([tuple(r) for r in sorted(seen)])
    model.fit = logistic(points[:, 1:], points[:, 0])
    return model


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05) -> tuple[float, ...]:
    """Logistic fit by Newton steps with a small ridge on the slopes; first the intercept, then the slopes."""
    a = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(a.shape[1])
    keep = np.diag([1e-6] + [ridge] * x.shape[1])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        g = a.T @ (p - y) + keep @ w
        step = np.linalg.solve((a * (p * (1 - p) + 1e-9)[:, None]).T @ a + keep, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in w)


def score(docs: DataFrame, model: ToxicityModel, keep: tuple[str, ...] = ("doc_id",), below: float | None = None) -> DataFrame:
    """The kept columns with score for every row of docs; below: instead, the kept columns of the rows that score less."""
    source = docs.select(*[col(c).alias(f"c{i}") for i, c in enumerate(keep)], F.col("text").alias("scored"))
    shape = ", ".join(f"c{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep)) + ", score double"

    def run(batches):
        restorer, known = Restorer(model.chars), {}
        for b in batches:
            text = b.column(b.num_columns - 1)
            scores = [model.score(model.evidence(restorer, text[i].as_py(), known)) for i in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(scores, pa.float64())], names=[*b.schema.names[:-1], "score"])

    out = source.mapInArrow(run, shape)
    named = [F.col(f"c{i}").alias(c) for i, c in enumerate(keep)]
    return out.select(*named, "score") if below is None else out.where(F.col("score") < below).select(*named)


def digest(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs."""
    scored = score(docs, train(docs, labels, per_class))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """The rows of docs that score below the threshold, columns as given."""
    return score(docs, train(docs, labels), tuple(docs.columns), threshold)
