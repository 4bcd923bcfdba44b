"""Quality classifier: a generalised additive model with pairwise interactions.

Each feature of a text has a lookup table over quantile bins. The tables are learnt by boosting that
visits the features in turn and adds a shallow tree on one feature at a time; the feature pairs with
the largest gain over the residuals get two-dimensional tables in the same way. A text is scored by
adding the entries of its bins, for a whole batch at once.

Scale: one narrow pass over all texts to score them, another over at most ``SAMPLE_ROWS`` labelled
texts to fit; the driver holds their features and the tables, both of bounded size.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from .common import fold_of, map_batches, utf8
from .labelled import SAMPLE_ROWS, labelled_sample, sigmoid

FEATURES = (
    "log bytes", "log words", "bytes per word", "upper share", "lower share", "digit share", "mark share", "symbol share", "shout share", "beyond ascii share", "symbol words",
    "upper words", "long words", "distinct words", "top word share", "again words", "again lines", "words per line", "short lines", "sentence ends",
)
_UPPER, _LOWER, _DIGIT = (bytes(range(a, b + 1)) for a, b in ((65, 90), (97, 122), (48, 57)))
_MARKS, _SYMBOLS, _SHOUTS, _HIGH = b".,;:'\"()-", b"#$%&*@^~|<>{}[]=+_\\/", b"!?", bytes(range(128, 256))


def text_features(text: str | None) -> list[float]:
    """The features of a whole text; those of an empty text are all 0."""
    raw = utf8(text)
    words = raw.split()
    n, m = len(raw), len(words)
    if not m:
        return [0.0] * len(FEATURES)
    share = lambda which: (n - len(raw.translate(None, which))) / n
    letters = max(1, n - len(raw.translate(None, _UPPER + _LOWER)))
    upper = (n - len(raw.translate(None, _UPPER))) / letters
    counts = Counter(words)
    pairs = len(set(zip(words, words[1:])))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    bare = raw.translate(None, _SYMBOLS)
    odd = sum(c for w, c in counts.items() if w.translate(None, _SYMBOLS + _SHOUTS) != w)
    return [
        np.log1p(n), np.log1p(m), n / m, upper, share(_LOWER), share(_DIGIT), share(_MARKS), (n - len(bare)) / n, share(_SHOUTS), share(_HIGH), odd / m,
        sum(c for w, c in counts.items() if w.isupper() and len(w) > 1) / m, sum(c for w, c in counts.items() if len(w) > 14) / m, len(counts) / m, max(counts.values()) / m,
        1 - pairs / max(1, m - 1), 1 - len(set(lines)) / len(lines), m / len(lines), sum(len(x) < 20 for x in lines) / len(lines), (raw.count(b".") + raw.count(b"!") + raw.count(b"?")) / m,
    ]


@dataclass
class AdditiveModel:
    """Lookup tables: ``cuts[f]`` are bin edges, ``tables[f]`` the entries; pairs share coarser edges."""

    base: float
    cuts: list[np.ndarray]
    tables: list[np.ndarray]
    coarse: list[np.ndarray]
    pairs: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for f, (cut, table) in enumerate(zip(self.cuts, self.tables)):
            out += table[np.searchsorted(cut, x[:, f], side="right")]
        for (f, g), table in self.pairs.items():
            out += table[np.searchsorted(self.coarse[f], x[:, f], side="right"), np.searchsorted(self.coarse[g], x[:, g], side="right")]
        return out


def _edges(values: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(values, np.linspace(0, 1, bins + 1)[1:-1])) if len(values) else np.zeros(0)


def _gain(g: np.ndarray, h: np.ndarray) -> np.ndarray:
    return g * g / (h + 1.0)


def _step(g: np.ndarray, h: np.ndarray, depth: int = 2) -> np.ndarray:
    """Leaf values of a shallow tree over ordered bins with gradients g and curvatures h."""
    if depth and len(g) > 1:
        gl, hl = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
        gains = _gain(gl, hl) + _gain(g.sum() - gl, h.sum() - hl)
        k = int(np.argmax(gains))
        if gains[k] > _gain(g.sum(), h.sum()) + 1e-9:
            return np.concatenate([_step(g[: k + 1], h[: k + 1], depth - 1), _step(g[k + 1 :], h[k + 1 :], depth - 1)])
    return np.full(len(g), g.sum() / (h.sum() + 1.0))


def _quadrants(g: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray]:
    """Best split of a two-dimensional histogram into four quadrants: its gain and leaf values."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    tg, th = cg[-1, -1], ch[-1, -1]
    ag, ah, bg, bh, og, oh = cg[:-1, -1:], ch[:-1, -1:], cg[-1:, :-1], ch[-1:, :-1], cg[:-1, :-1], ch[:-1, :-1]
    if not og.size:
        return 0.0, np.zeros_like(g)
    parts = [(og, oh), (ag - og, ah - oh), (bg - og, bh - oh), (tg - ag - bg + og, th - ah - bh + oh)]
    gains = sum(_gain(a, b) for a, b in parts)
    i, j = np.unravel_index(int(np.argmax(gains)), gains.shape)
    out = np.empty_like(g)
    for (a, b), at in zip(parts, (np.s_[: i + 1, : j + 1], np.s_[: i + 1, j + 1 :], np.s_[i + 1 :, : j + 1], np.s_[i + 1 :, j + 1 :])):
        out[at] = a[i, j] / (b[i, j] + 1.0)
    return float(gains[i, j] - _gain(tg, th)), out


def fit_additive(x: np.ndarray, y: np.ndarray, bins: int = 48, coarse_bins: int = 12, rounds: int = 120, pair_rounds: int = 40, n_pairs: int = 6, rate: float = 0.1) -> AdditiveModel:
    """Fit by cyclic boosting; without rows of both labels the model is a constant."""
    share = (y.sum() + 0.5) / (len(y) + 1)
    cuts, coarse = [_edges(x[:, f], bins) for f in range(x.shape[1])], [_edges(x[:, f], coarse_bins) for f in range(x.shape[1])]
    model = AdditiveModel(float(np.log(share / (1 - share))), cuts, [np.zeros(len(c) + 1) for c in cuts], coarse)
    if len(np.unique(y)) < 2:
        return model
    at = [np.searchsorted(c, x[:, f], side="right") for f, c in enumerate(cuts)]
    z = np.full(len(y), model.base)
    for _ in range(rounds):
        for f, table in enumerate(model.tables):
            p = sigmoid(z)
            step = rate * _step(np.bincount(at[f], y - p, len(table)), np.bincount(at[f], p * (1 - p), len(table)))
            table += step
            z += step[at[f]]
    low = [np.searchsorted(c, x[:, f], side="right") for f, c in enumerate(coarse)]
    size = [len(c) + 1 for c in coarse]

    def histogram(f: int, g: int) -> tuple[np.ndarray, np.ndarray]:
        p, cell = sigmoid(z), low[f] * size[g] + low[g]
        return np.bincount(cell, y - p, size[f] * size[g]).reshape(size[f], size[g]), np.bincount(cell, p * (1 - p), size[f] * size[g]).reshape(size[f], size[g])

    ranked = sorted(combinations(range(x.shape[1]), 2), key=lambda fg: -_quadrants(*histogram(*fg))[0])[:n_pairs]
    model.pairs = {fg: np.zeros((size[fg[0]], size[fg[1]])) for fg in ranked}
    for _ in range(pair_rounds):
        for (f, g), table in model.pairs.items():
            step = rate * _quadrants(*histogram(f, g))[1]
            table += step
            z += step[low[f], low[g]]
    return model


def featured(docs: DataFrame, extra: str = "") -> DataFrame:
    """(doc_id, extra columns, features) of ``docs(doc_id, text, extra)``."""
    kinds = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in ["doc_id", *extra.split()])
    return map_batches(docs, f"{kinds}, features array<double>", lambda b: {c: b.column(c) for c in ["doc_id", *extra.split()]} | {"features": [text_features(t) for t in b.column("text").to_pylist()]})


def quality_scores(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", modulus: int = 3, held_out: int = 1, sample_rows: int = SAMPLE_ROWS, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per input row: doc_id, columns ``carry`` of the row, held_out, score (0 to 1), predicted, log_odds.

    Learns from the text alone. Null and empty texts are scored with all features 0. Without labels of
    both kinds every score is the (smoothed) share of label 1. Repeated rows are scored alike; an empty
    table gives no rows.
    """
    sample = featured(labelled_sample(docs, labels, label, modulus, held_out, key, text, sample_rows), "label").select("doc_id", "label", "features").toPandas()
    sample = sample.sort_values("doc_id", kind="stable")
    x = np.stack(sample["features"].to_numpy()).astype(float) if len(sample) else np.zeros((0, len(FEATURES)))
    model = sent(docs.sparkSession, fit_additive(x, sample["label"].to_numpy(float)))
    base = docs.select(F.col(key).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), *carry)
    own = ["doc_id", *carry]
    kinds = ", ".join(f"`{c}` {base.schema[c].dataType.simpleString()}" for c in own)

    def make(batch: pa.RecordBatch) -> dict[str, object]:
        rows = np.array([text_features(t) for t in batch.column("text").to_pylist()], float).reshape(-1, len(FEATURES))
        z = opened(model).log_odds(rows)
        p = sigmoid(z)
        return {c: batch.column(c) for c in own} | {"score": p, "predicted": (p >= 0.5).astype(np.int32), "log_odds": z}

    scored = map_batches(base, f"{kinds}, score double, predicted int, log_odds double", make)
    return scored.select(*own, (fold_of(F.col("doc_id"), modulus) == held_out).alias("held_out"), "score", "predicted", "log_odds")
