"""Toxicity: maximum-scoring segments over token log-odds with Dirichlet priors.

Each word has a log-odds of occurring in toxic text, smoothed by an informative
Dirichlet prior (its share in both classes together). A word takes the highest log-odds
of itself and its known prefixes, so inflected forms of a stem count. A linear scan over
a document's scores, those of every place, finds every disjoint maximal-scoring segment.
In a segment a word counts once, so a passage is as toxic as its distinct words say, and
the same words elsewhere in the document change nothing. For random text the best segment follows an extreme-value law with
parameters lambda and K (lambda solves sum p(s) exp(lambda s) = 1), so a segment of
score S among n words is unexpected by lambda S - log(K n) nats; significant segments
add up to the document's evidence, which a logistic curve maps to 0..1.

Training uses at most ``train_rows`` labelled rows (least hash of the id), so the model
is small at any size of the corpus; every document is scored, over its whole text.

Defined results: an id with both labels counts as toxic; null, empty or blank text holds no segment and gets the score of no
evidence (below 0.5); repeated rows each get the same score; without both classes to
learn from, every word scores 0 and every document 0 to within 1e-13.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import words as W
from .shared import written

TRAIN_ROWS = 20_000
#: Strength of the prior in documents, least number of documents with a token, prefix lengths.
PRIOR, LEAST, PREFIXES = 50.0, 3, (4, 5, 6)
#: A token weighs the lower end of its log-odds, this many standard deviations down, and only if that is at least ODDS.
DOWN, ODDS = 1.0, 1.5
#: Scores are capped to this range of nats; a word without evidence costs a little.
CAP, COST = 8.0, -0.25
#: Offset of the model without both classes (a score of 1e-13), and the highest offset of a learnt one: no evidence is never toxic.
NONE, LEAST_DOUBT = -30.0, -1e-3


def forms(word: str) -> list[str]:
    """Names under which a word is looked up."""
    return [word, *(f"{word[:k]}~" for k in reversed(PREFIXES) if len(word) > k)]


def tokens(text: str) -> list[str]:
    return [x for x in (w.strip("\"'.,;:!?()[]{}*#$%&|<>-_/\\~`").lower() for w in text.split()) if x]


def count_forms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each form in the slice: toxic and other documents that hold it."""
    for batch in W.pieces(batches, "_text", 4 << 20):
        seen: dict[str, list[int]] = {}
        for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            for form in {f for w in set(tokens(text or "")) for f in forms(w)}:
                seen.setdefault(form, [0, 0])[toxic] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array([x[1] for x in seen.values()], pa.int64()), pa.array([x[0] for x in seen.values()], pa.int64())], ["form", "toxic", "clean"])


class Model:
    def __init__(self, weights: dict[str, float], lam: float, log_k: float, slope: float = 1.0, offset: float = 0.0):
        self.weights, self.lam, self.log_k, self.slope, self.offset = weights, lam, log_k, slope, offset

    def word(self, word: str) -> float:
        return max([x for form in forms(word) if (x := self.weights.get(form)) is not None], default=COST)

    def row(self, text: str | None, memo: dict[str, float]) -> tuple[list[str], list[float]]:
        """Words of a text and their log-odds, each at every place."""
        words, out = tokens(text or ""), []
        for w in words:
            x = memo.get(w)
            if x is None:
                if len(memo) > 100_000:
                    memo.clear()
                x = memo[w] = self.word(w)
            out.append(x)
        return words, out

    def segments(self, scores: list[float]) -> list[tuple[int, int, float]]:
        """Every disjoint maximal-scoring segment (first, end, score): a linear scan that keeps, for each open candidate, the running total before and after it."""
        open_: list[list[float]] = []
        total = 0.0
        for i, s in enumerate(scores):
            before, total = total, total + s
            if s <= 0:
                continue
            now = [i, i + 1, before, total]
            while open_:
                j = len(open_) - 1
                while j >= 0 and open_[j][2] >= now[2]:
                    j -= 1
                if j < 0 or open_[j][3] >= now[3]:
                    break
                now = [open_[j][0], i + 1, open_[j][2], total]
                del open_[j:]
            open_.append(now)
        return [(int(a), int(b), right - left) for a, b, left, right in open_]

    def evidence(self, words: list[str], scores: list[float]) -> tuple[float, list[tuple[int, int, float]]]:
        """Significant passages. A passage lies within a segment of the scan, whose score, with every repetition counted, bounds its own."""
        cut = self.log_k + np.log(max(len(scores), 1))
        near = [(a, b) for a, b, s in self.segments(scores) if self.lam * s > cut]
        found = [(a, b, e) for x, y in near for a, b, s in distinct_segments(words, scores, x, y, cut / self.lam) if (e := self.lam * s - cut) > 0]
        return float(np.log1p(sum(e for *_, e in found))), found

    def score(self, evidence: float) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.slope * evidence + self.offset, -30, 30))))


def distinct_segments(words: list[str], scores: list[float], first: int, end: int, least: float = 0.0) -> list[tuple[int, int, float]]:
    """The segments above least in first..end, in order: the best one, and in the same way those left and right of it. The log-odds speak of documents that hold a word, so in a segment a word counts once and costs COST at its other places.

    A later start gains at least as much of each word as an earlier one, so a start that has no lead over the next never gets one. The scan keeps the live starts' leads; a word changes two of them."""
    out: list[tuple[int, int, float]] = []
    todo = [(first, end)]
    while todo:
        a, b = todo.pop()
        lead: dict[int, float] = {}
        before: dict[int, int] = {}
        last: dict[str, int] = {}
        head, total, best, at = a, 0.0, 0.0, (a, b)
        for i in range(a, b):
            x = scores[i]
            lead[i], before[i] = x, _live(i - 1, lead, before)
            total += x
            weak = [i]
            if x > 0:
                k = _live(last.get(words[i], -1), lead, before)
                last[words[i]] = i
                if k >= 0:
                    lead[k] -= x - COST
                    total -= x - COST
                    weak.append(k)
            for k in weak:
                while k >= 0 and lead.get(k, 1.0) <= 0:
                    lost, p = lead.pop(k), _live(before[k], lead, before)
                    before[k] = p
                    if p >= 0:
                        lead[p] += lost
                    else:
                        total, head = total - lost, k + 1
                    k = p
            if not lead:
                total, head = 0.0, i + 1
            while head <= i and head not in lead:
                head += 1
            if total > best + 1e-9:  # of equal ones the first
                best, at = total, (head, i + 1)
            elif best > 0 and head >= at[1]:
                # no later segment begins before the end of the best one
                break
        if best > 0:
            todo.append((at[1], b))
        if best > max(least, 0.0):
            out.append((*at, best))
            todo.append((a, at[0]))
    return sorted(out)


def _live(k: int, lead: dict[int, float], before: dict[int, int]) -> int:
    """The last live start up to k, or -1; shortens the way for the next search."""
    way = []
    while k >= 0 and k not in lead:
        way.append(k)
        k = before.get(k, -1)
    for x in way:
        before[x] = k
    return k


def _calibrate(scores: np.ndarray, counts: np.ndarray) -> tuple[float, float]:
    """lambda and log K of the best segment's extreme-value law, from the scores of words in clean text and how often each occurs (K by its usual bound, the decay times the mean loss)."""
    if not (scores > 0).any():
        return 1.0, 0.0
    low, high = 1e-6, 1.0
    excess = lambda x: np.average(np.exp(np.minimum(x * scores, 700)), weights=counts) - 1
    while excess(high) < 0 and high < 64:
        high *= 2
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    return low, float(np.log(max(low * abs(np.average(scores, weights=counts)), 1e-9)))


def count_scores(model: Model):
    """How often each score occurs, at all places of the texts of the slice; there are no more scores than weights, and one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[str, float] = {}
        for batch in W.pieces(batches, "_text", 4 << 20):
            seen: Counter[float] = Counter()
            for text in batch.column(0).to_pylist():
                seen.update(model.row(text, memo)[1])
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.float64()), pa.array(list(seen.values()), pa.int64())], ["score", "n"])

    return run


def fit(docs: DataFrame, labels: DataFrame, usable: Column, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text", train_rows: int = TRAIN_ROWS) -> Model:
    """usable: the rows of labels that may be learnt from."""
    known = labels.where(usable & F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("_toxic")).groupBy("_id").agg(F.max("_toxic").alias("_toxic"))
    known = known.orderBy(F.xxhash64("_id"), "_id").limit(train_rows)
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).join(F.broadcast(known), "_id").select("_text", "_toxic")
    rows = written(rows, docs.sparkSession)
    counts = rows.mapInArrow(count_forms, "form string, toxic long, clean long").groupBy("form").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")).where(F.col("toxic") + F.col("clean") >= LEAST)
    size = rows.groupBy("_toxic").count().collect()
    size = {r["_toxic"]: r["count"] for r in size}
    if len(size) < 2:
        return Model({}, 1.0, 0.0, offset=NONE)
    t, c = size[1], size[0]
    share = (F.col("toxic") + F.col("clean")) / F.lit(float(t + c))
    odds = lambda y, n: F.log((F.col(y) + PRIOR * share) / (n + PRIOR - F.col(y) - PRIOR * share))
    spread = 1 / (F.col("toxic") + PRIOR * share) + 1 / (F.col("clean") + PRIOR * share)
    weighed = counts.withColumn("w", odds("toxic", t) - odds("clean", c) - DOWN * F.sqrt(spread))
    # the bounded sample bounds the number of tokens that are surely toxic
    kept = weighed.where(F.col("w") > ODDS).select("form", "w").collect()
    weights = {r["form"]: float(min(r["w"], CAP)) for r in kept}
    model = Model(weights, 1.0, 0.0)
    spread_of = rows.where("_toxic = 0").select("_text").mapInArrow(count_scores(model), "score double, n long").groupBy("score").agg(F.sum("n").alias("n")).orderBy("score").collect()
    # the highest weight occurs once, so that a decay exists
    values, times = [r["score"] for r in spread_of] or [COST], [r["n"] for r in spread_of] or [1]
    model.lam, model.log_k = _calibrate(np.array([*values, max([*weights.values(), 1.0])]), np.array([*times, 1.0]))
    seen = rows.select(F.pandas_udf(_evidence(model), "double")("_text").alias("e"), "_toxic").toPandas()
    model.slope, model.offset = _logistic(seen["e"].to_numpy(), seen["_toxic"].to_numpy())
    return model


def _evidence(model: Model):
    def run(text: pd.Series) -> pd.Series:
        return pd.Series([model.evidence(*model.row(x, {}))[0] for x in text], dtype="float64")

    return run


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05) -> tuple[float, float]:
    """Two-parameter logistic regression with a small ridge, by Newton steps that are halved until the loss falls."""
    at = np.array([0.1, -1.0])

    def loss(t: np.ndarray) -> float:
        z = t[0] * x + t[1]
        return float((np.logaddexp(0, z) - y * z).sum() + ridge / 2 * (t @ t))

    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(at[0] * x + at[1], -30, 30)))
        w = np.maximum(p * (1 - p), 1e-9)
        g = np.array([((p - y) * x).sum(), (p - y).sum()]) + ridge * at
        h = np.array([[(w * x * x).sum(), (w * x).sum()], [(w * x).sum(), w.sum()]]) + ridge * np.eye(2)
        step, before = np.linalg.solve(h, g), loss(at)
        while loss(at - step) > before and abs(step).max() > 1e-10:
            step = step / 2
        at = at - step
        if abs(step).max() < 1e-9:
            break
    return float(max(at[0], 1e-6)), float(min(at[1], LEAST_DOUBT))


def crc_fold(value: int | None) -> int:
    return zlib.crc32(str(value).encode()) % 5


def scorer(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[str, float] = {}
        for batch in W.pieces(batches, "_text"):
            scores, passages = [], []
            for text in batch.column(0).to_pylist():
                split, row = model.row(text, memo)
                e, found = model.evidence(split, row) if any(x > 0 for x in row) else (0.0, [])
                scores.append(model.score(e))
                passages.append([{"first": a, "end": b, "evidence": float(v)} for a, b, v in found])
            kind = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64()), ("evidence", pa.float64())]))
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(scores, pa.float64()), pa.array(passages, kind)], [*batch.schema.names[1:], "score", "passages"])

    return run


def score(docs: DataFrame, model: Model, text_col: str = "text", carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, score (0 to 1) and passages (first and end token, evidence in nats)."""
    kinds = dict(docs.dtypes)
    names = [f"_c{i}" for i in range(len(carry))]
    rows = docs.select(F.col(text_col).alias("_text"), *(F.col(c).alias(n) for c, n in zip(carry, names, strict=True)))
    schema = "".join(f"{n} {kinds[c]}, " for c, n in zip(carry, names, strict=True)) + "score double, passages array<struct<first: long, end: long, evidence: double>>"
    return rows.mapInArrow(scorer(model), schema).withColumnsRenamed(dict(zip(names, carry, strict=True)))
