"""Toxic passages as maximum-scoring segments.

Words, and the beginnings that words share, get log-odds between toxic and other labelled texts, with
an informative Dirichlet prior in proportion to their overall counts; counts are numbers of texts,
so a line that one text repeats counts once, and the near copies of a text share one count. A word scores as the clearest of its own and its
beginnings' log-odds. Along a text a scan in linear time finds every maximal
segment of positive sum; extreme-value statistics of such segments (the decay rate at which the
expected exponential of a background word is one, and a constant fitted on texts that are not toxic)
tell how surprising a segment is in a text of its length. A text's score is a logistic function of
its best and of its significant segments.

Scale: one pass over all texts, narrow; statistics and the fit come from at most ``SAMPLE_ROWS``
labelled texts. The lexicon has every unit that passes the z-score, however many: such a unit stands in
several of those texts, so what is broadcast is bounded by the sample, not by the documents.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..storage import written
from .common import alnum_words, fold_of, map_batches, mix64, two_columns
from .labelled import SAMPLE_ROWS, labelled_sample, sigmoid

#: Words whose scores a worker remembers between texts.
CACHE_WORDS = 400_000
#: What each word costs a segment, so that a segment ends when no toxic word follows.
DRIFT = 0.1
#: Segments with fewer expected in a text by chance are significant.
SIGNIFICANT = 0.05


#: Lengths, in characters, of the word beginnings that are units of their own.
BEGINNINGS = (4, 5, 6, 7, 8)


def units(word: bytes) -> list[bytes]:
    """The word as a unit, and its proper beginnings."""
    text = word.decode("utf-8", "ignore")
    return [b"=" + word, *(b"^" + text[:n].encode() for n in BEGINNINGS if n < len(text))]


def maximal_segments(places: np.ndarray, gains: np.ndarray, costs: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (first place, last place, sum), in linear time.

    ``gains`` are positive scores at rising ``places``; ``costs[k]`` is the (negative or zero) sum of
    what lies between place k-1 and place k. Keeps a list of disjoint candidates, each with the sum
    before it and up to its end, and merges back whenever a candidate's left sum is exceeded.
    """
    found: list[list[float]] = []  # first, last, sum before, sum at end
    total = 0.0
    back: list[int] = []  # for each candidate, the nearest earlier one with a smaller left sum, or -1
    for place, gain, cost in zip(places.tolist(), gains.tolist(), costs.tolist()):
        left = total + cost
        total = left + gain
        first, right = place, total
        while True:
            j = len(found) - 1
            while j >= 0 and found[j][2] >= left:
                j = back[j]
            if j < 0 or found[j][3] >= right:
                found.append([first, place, left, right])
                back.append(j)
                break
            first, left = found[j][0], found[j][2]
            del found[j:], back[j:]
    return [(int(a), int(b), d - c) for a, b, c, d in found]


def signatures(words: list[bytes], n: int = 3) -> list[int]:
    """``n`` smallest hashes of the text's five-word shingles, each under a hash function of its own."""
    codes = np.fromiter(map(crc32, words), np.uint64, len(words)) if words else np.zeros(1, np.uint64)
    size = max(1, len(codes) - 4)
    mixed = np.zeros(size, np.uint64)
    for k in range(min(5, len(codes))):
        mixed = mix64(mixed + codes[k : k + size] + np.uint64(k + 1))
    return [int(mix64(mixed + np.uint64(1000 + k)).min() >> np.uint64(1)) for k in range(n)]


def with_copy_weights(sample: DataFrame) -> DataFrame:
    """(text, label, weight): one over the number of texts that share a signature, by the signature that fewest share.

    A shared passage seldom holds the smallest hash under every function, so it alone joins no texts.
    """

    def sign(batch: pa.RecordBatch) -> dict[str, object]:
        own = np.array([signatures(alnum_words(t)) for t in batch.column("text").to_pylist()], np.int64).reshape(-1, 3)
        return {"text": batch.column("text"), "label": batch.column("label"), "s0": own[:, 0], "s1": own[:, 1], "s2": own[:, 2]}

    out = signed = written(map_batches(sample, "text string, label int, s0 bigint, s1 bigint, s2 bigint", sign), "toxic-signed")
    for s in ("s0", "s1", "s2"):  # at most as many signatures as the sample has rows
        out = out.join(F.broadcast(signed.groupBy(s).agg(F.count(F.lit(1)).alias("n" + s))), s)
    return written(out.select("text", "label", (1.0 / F.least("ns0", "ns1", "ns2")).alias("weight")), "toxic-weighted")


@dataclass
class SegmentModel:
    """(z-score, score) of known units, the score of words without any, and the statistics of segments."""

    known: dict[bytes, tuple[float, float]]
    other: float
    rate: float
    constant: float
    weights: np.ndarray

    def scores(self, words: list[bytes]) -> np.ndarray:
        cache = self.__dict__.setdefault("cache", {})
        if len(cache) > CACHE_WORDS:
            cache.clear()
        for w in set(words).difference(cache):
            found = [self.known[u] for u in units(w) if u in self.known]
            cache[w] = max(found)[1] if found else self.other
        return np.fromiter(map(cache.__getitem__, words), float, len(words))

    def segments(self, words: list[bytes]) -> list[tuple[int, int, float]]:
        s = self.scores(words)
        places = np.flatnonzero(s > 0)
        if not len(places):
            return []
        sums = np.concatenate([[0.0], np.cumsum(s)])
        before = np.concatenate([[0], places[:-1] + 1])
        return maximal_segments(places, s[places], sums[places] - sums[before])

    def bits(self, score: float, n: int) -> float:
        """Minus the log of how many segments of this score a text of n background words has by chance."""
        return self.rate * score - np.log(max(self.constant * n, 1e-12))

    def features(self, words: list[bytes]) -> tuple[list[float], list[tuple[int, int, float]]]:
        raw = self.segments(words)
        found = [(a, b, self.bits(s, len(words))) for a, b, s in raw]
        kept = [x for x in found if x[2] >= -np.log(SIGNIFICANT)]
        best = max((x[2] for x in found), default=0.0)
        top = max((s for _, _, s in raw), default=0.0)
        return [1.0, min(max(best, 0.0), 60.0), float(np.log1p(len(kept))), min(top, 30.0)], kept


def dirichlet_log_odds(toxic: np.ndarray, other: np.ndarray, n: float, m: float, prior: float = 20.0) -> tuple[np.ndarray, np.ndarray]:
    """(log-odds, z-score) of each unit that stands in ``toxic`` of n and ``other`` of m texts.

    The prior holds ``prior`` texts in proportion to the unit's overall share, and half a text.
    """
    alpha = 0.5 + prior * (toxic + other) / max(1.0, n + m)
    a, b = toxic + alpha, other + alpha
    delta = np.log(a / (n + prior + 1 - a)) - np.log(b / (m + prior + 1 - b))
    return delta, delta / np.sqrt(1 / a + 1 / b)


def decay_rate(scores: np.ndarray, shares: np.ndarray) -> float:
    """The positive r at which the mean of exp(r * score) is one; needs a negative mean."""
    f = lambda r: float((shares * np.exp(np.minimum(r * scores, 600))).sum()) - 1
    low, high = 1e-6, 1e-3
    if (scores * shares).sum() >= 0 or not (scores > 0).any():
        return 1.0
    while f(high) < 0 and high < 1e3:
        low, high = high, high * 2
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if f(mid) < 0 else (low, mid)
    return (low + high) / 2


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = sigmoid(x @ w)
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w)), x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def fit_segments(sample: DataFrame, least_z: float = 3.5, prior: float = 20.0) -> SegmentModel:
    """Fit on ``sample(doc_id, text, label)``, a table of bounded size."""

    def count(batch: pa.RecordBatch) -> dict[str, object]:
        toxic, other = defaultdict(float), defaultdict(float)
        for t, y, share in zip(*(batch.column(c).to_pylist() for c in ("text", "label", "weight"))):
            own = toxic if y else other
            for u in {b""} | {u for w in set(alnum_words(t)) for u in units(w)}:
                own[u] += share
        words = list(toxic.keys() | other.keys())
        return {"word": words, "toxic": [toxic.get(w, 0.0) for w in words], "other": [other.get(w, 0.0) for w in words]}

    counts = map_batches(with_copy_weights(sample), "word binary, toxic double, other double", count).groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))
    counts = written(counts, "word-counts")
    totals = counts.where(F.length("word") == 0).agg(F.sum("toxic"), F.sum("other")).first()
    n, m = float(totals[0] or 0), float(totals[1] or 0)
    if not n or not m:
        share = 0.999 if n else 0.001
        return SegmentModel({}, -DRIFT, 1.0, 1.0, np.array([np.log(share / (1 - share)), 0.0, 0.0, 0.0]))
    # The units that pass the z-score, judged where their counts are; see dirichlet_log_odds.
    alpha = 0.5 + prior * (F.col("toxic") + F.col("other")) / max(1.0, n + m)
    units_ = counts.where(F.length("word") > 0).select("word", "toxic", "other", (F.col("toxic") + alpha).alias("a"), (F.col("other") + alpha).alias("b"))
    lean = (F.log(F.col("a") / (n + prior + 1 - F.col("a"))) - F.log(F.col("b") / (m + prior + 1 - F.col("b")))) / F.sqrt(1 / F.col("a") + 1 / F.col("b"))
    own = units_.where(F.abs(lean) >= least_z - 1e-6).select("word", "toxic", "other").orderBy("word").toPandas()
    toxic, other = own["toxic"].to_numpy(float), own["other"].to_numpy(float)
    delta, z = dirichlet_log_odds(toxic, other, n, m, prior)
    score = np.where(np.abs(z) >= least_z, np.maximum(delta, -1.0), 0.0) - DRIFT
    words = {bytes(w): (float(abs(c)), float(s)) for w, c, s in zip(own["word"], z, score) if abs(c) >= least_z}
    # The background: how often a known unit stands in a text that is not toxic; the rest costs the drift.
    total = float(counts.where(F.substring("word", 1, 1) == F.lit(b"=")).agg(F.sum("other")).first()[0] or 1.0)
    share = np.append(other[np.abs(z) >= least_z] / total, 0.0)
    share[-1] = max(0.0, 1.0 - share.sum())
    rate = decay_rate(np.append(score[np.abs(z) >= least_z], -DRIFT), share / share.sum())
    model = SegmentModel(words, -DRIFT, rate, 1.0, np.zeros(4))
    first = sent(sample.sparkSession, model)

    def best(batch: pa.RecordBatch) -> dict[str, object]:
        rows = [alnum_words(t) for t in batch.column("text").to_pylist()]
        return {"n": [len(w) for w in rows], "scores": [[s for _, _, s in opened(first).segments(w)] for w in rows]}

    clean = written(map_batches(sample.where("label = 0"), "n bigint, scores array<double>", best), "toxic-segments")
    scores = clean.select(F.explode("scores").alias("s"))
    at = scores.agg(F.percentile("s", F.lit(0.75))).first()[0]
    if at is not None:
        # The constant: as many chance segments over the upper quartile as the clean texts have.
        over, size = scores.where(F.col("s") >= at).count(), clean.agg(F.sum("n")).first()[0]
        model.constant = float(over * np.exp(min(rate * at, 50.0)) / max(1, size))
    second = sent(sample.sparkSession, model)

    def features(batch: pa.RecordBatch) -> dict[str, object]:
        return {"label": batch.column("label"), "x": [opened(second).features(alnum_words(t))[0] for t in batch.column("text").to_pylist()]}

    rows = map_batches(sample, "label int, x array<double>", features).toPandas()
    model.weights = _logistic(np.stack(rows["x"].to_numpy()).astype(float), rows["label"].to_numpy(float))
    return model


def toxicity_scores(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", modulus: int = 5, held_out: int = 0, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """One row per input row: doc_id, held_out, score (0 to 1), predicted, passages.

    ``passages`` are the significant segments (first word, end, minus log of the number expected by
    chance). Null and empty texts have no segment and get the score of such texts. Without labels of
    both kinds every text has one score. Repeated rows are scored alike; an empty table gives none.
    """
    sample = written(labelled_sample(docs, labels, label, modulus, held_out, key, text, sample_rows), "toxic-sample")
    model = sent(docs.sparkSession, fit_segments(sample))
    base = two_columns(docs, key, text)
    kind = base.schema["doc_id"].dataType.simpleString()
    passage = pa.struct([("first", pa.int64()), ("end", pa.int64()), ("surprise", pa.float64())])

    def make(batch: pa.RecordBatch) -> dict[str, object]:
        own = [opened(model).features(alnum_words(t)) for t in batch.column("text").to_pylist()]
        p = sigmoid(np.array([x for x, _ in own], float).reshape(-1, 4) @ opened(model).weights)
        found = pa.array([[{"first": a, "end": b + 1, "surprise": s} for a, b, s in kept] for _, kept in own], pa.list_(passage))
        return {"doc_id": batch.column("doc_id"), "score": p, "predicted": (p >= 0.5).astype(np.int32), "passages": found}

    scored = map_batches(base, f"doc_id {kind}, score double, predicted int, passages array<struct<first: bigint, `end`: bigint, surprise: double>>", make)
    return scored.select("doc_id", (fold_of(F.col("doc_id"), modulus) == held_out).alias("held_out"), "score", "predicted", "passages")
