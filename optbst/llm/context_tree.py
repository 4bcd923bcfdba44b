"""Language-model scores by context-tree weighting, beside a word-frequency baseline.

A text is a sequence of bytes and an end mark. Each byte is eight binary choices (its binary
decomposition); each choice has a tree of contexts, the preceding bytes up to ``DEPTH``. Every node
keeps how often the choice was 0 or 1 and estimates it by Krichevsky and Trofimov's rule. A node's
weighted probability is half its own estimate of what it saw and half the product of its children's;
so the posterior weight of stopping at a depth is known for every node, and a prediction mixes the
estimates of all depths along the context.

Scale. One pass counts (context, byte) and words over all texts, pre-aggregated for each batch. The
counts are cut into ranges of contexts, latest byte first, that never part contexts with the same
three latest bytes; ranges are weighted bottom-up by independent tasks, and depths 2 and 1 are
raised from the sums of the depth below in the same way. Only the 255 x 256 nodes of depth 1 (a
fixed bound) meet in one place. Texts are then scored in chunks: a chunk sends its distinct keys,
packed, to the shards of the answers, and the packed answers come back in the same order. A shard is
read once, followed by the chunks that ask it as a stream, so its task holds the shard and one packed
question however many chunks there are; the model is never copied, and nothing that grows with the
data is broadcast or collected. A chunk's texts are looked at slice by slice, long texts in pieces,
so a task holds the chunk's distinct keys and one slice. A key is a context and byte, or a word's
63-bit hash (two of a billion words share one with a probability of about one in twenty).
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..storage import written
from .common import fold_of, sliced, two_columns, utf8, word_keys

DEPTH = 5
#: Latest bytes that rows of one range share; contexts are at least this long.
SHARD = 3
#: Distinct (context, byte) rows of a range, about.
RANGE_ROWS = 200_000
#: Stands before a text and ends it; no UTF-8 text has this byte.
MARK = 0xFF
#: Text bytes that a scoring chunk holds, about.
CHUNK_BYTES = 12 << 20
#: Keys of a shard of the answers, about.
SHARD_KEYS = 250_000
#: Text bytes looked at together, and most texts of such a slice.
SLICE_BYTES, SLICE_TEXTS = 1 << 20, 1 << 16


def log_gamma_half(x: np.ndarray) -> np.ndarray:
    """ln Gamma(x) for x >= 0.5, by Stirling's series after a shift of 8."""
    x = np.asarray(x, float)
    y, shift = x + 8, np.zeros_like(x)
    for k in range(8):
        shift += np.log(x + k)
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - shift


def log_kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """ln of Krichevsky and Trofimov's probability of a sequence with these counts."""
    return log_gamma_half(zeros + 0.5) + log_gamma_half(ones + 0.5) - 2 * log_gamma_half(np.array(0.5)) - log_gamma_half(zeros + ones + 1.0)


@dataclass
class Slice:
    """Some lower-cased texts, or a piece of a long one: bodies, the bytes before each, whether it ends its text, the text's number."""

    bodies: list[bytes] = field(default_factory=list)
    heads: list[bytes] = field(default_factory=list)
    ends: list[bool] = field(default_factory=list)
    numbers: list[int] = field(default_factory=list)


_BLANK = re.compile(rb"[\x09-\x0D\x20]")


def text_slices(texts: Iterable[str], depth: int, most: int = SLICE_BYTES) -> Iterator[Slice]:
    """Lower-cased texts in slices of about ``most`` bytes; a longer text is cut behind blanks, so no word is."""
    own, size, mark = Slice(), 0, bytes([MARK]) * depth
    for number, t in enumerate(texts):
        raw, at, head = utf8(t).lower(), 0, mark
        while True:
            end = len(raw)
            if end - at > most and (found := _BLANK.search(raw, at + most)):
                end = found.end()
            if own.bodies and (size + end - at > most or len(own.bodies) >= SLICE_TEXTS - 1):
                yield own
                own, size = Slice(), 0
            own.bodies.append(raw[at:end]), own.heads.append(head), own.ends.append(end == len(raw)), own.numbers.append(number)
            size += end - at
            if end == len(raw):
                break
            head, at = (head + raw[max(at, end - depth) : end])[-depth:], end
    if own.bodies:
        yield own


def gram_codes(own: Slice, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(codes, how many of each body) at every byte and end mark; a code has the context, latest byte first, and then the byte.

    The latest context byte is the most significant, so a shorter context is a prefix of the number.
    """
    mark = bytes([MARK])
    data = np.frombuffer(b"".join(x for h, t, e in zip(own.heads, own.bodies, own.ends) for x in (h, t, mark if e else b"")), np.uint8).astype(np.int64)
    lengths = np.array([len(t) + e for t, e in zip(own.bodies, own.ends)], np.int64)
    code = data[depth:].copy()
    for k in range(1, depth + 1):
        code |= data[depth - k : len(data) - k] << (8 * (depth + 1 - k))
    # The bytes before a body are no symbols of it.
    starts = np.cumsum(lengths + depth)[:-1]
    keep = np.ones(len(code), bool)
    keep[((starts - depth)[:, None] + np.arange(depth)).ravel()] = False
    return code[keep], lengths


def choices(codes: np.ndarray, depth: int, at_depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(node keys, outcomes), both with a row for each of the eight choices, for contexts cut to ``at_depth``.

    A key is the context prefix, then a byte with the symbol's bits before the choice behind a leading 1.
    """
    symbol, context = codes & 255, (codes >> (8 * (depth + 1 - at_depth))) << 8
    bits = np.arange(8)[:, None]
    return context | (1 << bits) | (symbol >> (8 - bits)), (symbol >> (7 - bits)) & 1


class Level:
    """Nodes of one depth: sorted keys, counts, own and weighted log-probability, posterior weight of stopping."""

    def __init__(self, keys: np.ndarray, zeros: np.ndarray, ones: np.ndarray):
        self.keys, self.zeros, self.ones = keys, zeros, ones
        self.own = log_kt(zeros, ones)
        self.weighted = self.own
        self.stop = np.ones(len(keys))

    def weigh(self, below: np.ndarray) -> None:
        """Mix the own estimate with the children's product, half and half."""
        self.weighted = np.logaddexp(self.own, below) - math.log(2)
        self.stop = np.exp(self.own - math.log(2) - self.weighted)

    def frame(self) -> pd.DataFrame:
        return pd.DataFrame({"node": self.keys, "zeros": self.zeros, "ones": self.ones, "weighted": self.weighted})


def raised(keys: np.ndarray, zeros: np.ndarray, ones: np.ndarray, weighted: np.ndarray) -> Level:
    """The parents' level of nodes of one depth, weighted."""
    up, inverse = np.unique(((keys >> 16) << 8) | (keys & 255), return_inverse=True)
    level = Level(up, np.bincount(inverse, zeros, len(up)), np.bincount(inverse, ones, len(up)))
    level.weigh(np.bincount(inverse, weighted, len(up)))
    return level


def build_levels(codes: np.ndarray, counts: np.ndarray, depth: int, top: int) -> list[Level]:
    """Levels ``top`` to ``depth``, weighted bottom-up. Codes without a count leave no node."""
    seen = counts > 0
    keys, outcome = choices(codes[seen], depth, depth)
    n = np.broadcast_to(counts[seen].astype(float), keys.shape).ravel()
    keys, outcome = keys.ravel(), outcome.ravel()
    own, inverse = np.unique(keys, return_inverse=True)
    levels = [Level(own, np.bincount(inverse, n * (1 - outcome), len(own)), np.bincount(inverse, n * outcome, len(own)))]
    for _ in range(depth - top):
        low = levels[0]
        levels.insert(0, raised(low.keys, low.zeros, low.ones, low.weighted))
    return levels


def predict(levels: list[Level], codes: np.ndarray, depth: int, top: int, tail: np.ndarray | None = None) -> np.ndarray:
    """Probability of each code's outcomes (rows: the eight choices), mixing depths ``top`` and deeper.

    An unseen node predicts one half. ``tail`` are the predictions below the deepest level, if any.
    """
    out = np.full((8, len(codes)), 0.5) if tail is None else tail
    for d in range(len(levels) - 1, -1, -1):
        node = levels[d]
        if not len(node.keys):
            out = np.full((8, len(codes)), 0.5)
            continue
        keys, outcome = choices(codes, depth, top + d)
        at = np.minimum(np.searchsorted(node.keys, keys), len(node.keys) - 1)
        known = node.keys[at] == keys
        hit = np.where(outcome == 1, node.ones[at], node.zeros[at])
        own = (hit + 0.5) / (node.zeros[at] + node.ones[at] + 1.0)
        out = np.where(known, node.stop[at] * own + (1 - node.stop[at]) * out, 0.5)
    return out


def grouped(values: np.ndarray, sizes: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct values in order; then, with equal values together, the place of each value among them and its body.

    ``sizes`` says how many values in a row belong to each body. Values of few enough ``bits`` are sorted
    together with their body as one integer.
    """
    owner = np.repeat(np.arange(len(sizes), dtype=np.int64), sizes)
    if bits <= 47:
        both = np.sort((values << 16) | owner)
        values, owner = both >> 16, both & 0xFFFF
    elif bits == 48:
        both = np.sort((values.astype(np.uint64) << np.uint64(16)) | owner.astype(np.uint64))
        values, owner = (both >> np.uint64(16)).astype(np.int64), (both & np.uint64(0xFFFF)).astype(np.int64)
    else:
        order = np.argsort(values, kind="stable")
        values, owner = values[order], owner[order]
    if not len(values):
        return values, owner, owner
    new = np.concatenate([[True], values[1:] != values[:-1]])
    return values[new], np.cumsum(new) - 1, owner


def sorted_distinct(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values in order, and how often each stands in ``x``."""
    x = np.sort(x)
    first = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)
    return x[first], np.diff(np.append(first, len(x)))


def _merged(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    own, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    return own, np.bincount(inverse, np.concatenate(counts), len(own)).astype(np.int64)


def _counter(depth: int, most: int = 1_000_000):  # noqa: ANN202
    """(key, n) over a partition: training counts of all keys, merged before they leave in parts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys: list[np.ndarray] = []
        counts: list[np.ndarray] = []

        def leave() -> pa.RecordBatch:
            own, n = _merged(keys, counts)
            keys.clear(), counts.clear()
            return pa.RecordBatch.from_arrays([pa.array(own), pa.array(n)], names=["key", "n"])

        for batch in (part for whole in batches for part in sliced(whole)):
            for held in (False, True):
                for own in text_slices(batch.column("text").filter(pc.equal(batch.column("held_out"), held)).to_pylist(), depth):
                    for part in (gram_codes(own, depth)[0], word_keys(own.bodies)[0]):
                        distinct, n = sorted_distinct(part)
                        keys.append(distinct)
                        counts.append(n * (not held))
                    if sum(map(len, keys)) > 2 * most:
                        merged = _merged(keys, counts)
                        keys[:], counts[:] = [merged[0]], [merged[1]]
                        if len(merged[0]) > most:
                            yield leave()
        if keys:
            yield leave()

    return run


_NODES = "node bigint, zeros double, ones double, weighted double"


def _range_nodes(depth: int):  # noqa: ANN202
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return build_levels(pdf["gram"].to_numpy(), pdf["n"].to_numpy(), depth, SHARD)[0].frame()

    return run


def _raise(pdf: pd.DataFrame) -> pd.DataFrame:
    return raised(*(pdf[c].to_numpy() for c in ("node", "zeros", "ones", "weighted"))).frame()


def _level(pdf: pd.DataFrame) -> Level:
    """A weighted level from its rows in any order."""
    own = pdf.sort_values("node")
    level = Level(own["node"].to_numpy(np.int64), own["zeros"].to_numpy(float), own["ones"].to_numpy(float))
    level.weighted = own["weighted"].to_numpy(float)
    level.stop = np.exp(level.own - math.log(2) - level.weighted)
    return level


def language_model_scores(docs: DataFrame, key: str = "doc_id", text: str = "text", modulus: int = 7, held_out: int = 2, depth: int = DEPTH, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """One row per input row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte.

    Learns from rows outside the held-out fold; A-Z count as a-z. ``score`` is log10 of the model's
    probability of the bytes and the end mark. The base scores words between blanks and one end token
    by their smoothed shares. Null and empty texts have the end only. Without training rows every
    choice has probability one half and the base counts are 0. A null key belongs to the fold of the
    empty text. ``depth`` is at least 3. Repeated rows are learnt and scored each for itself; an empty table gives no rows.
    """
    base = two_columns(docs, key, text).withColumn("held_out", fold_of(F.col("doc_id"), modulus) == held_out)
    counts = base.mapInArrow(_counter(depth), "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n"))
    counts = written(counts, "lm-counts")
    facts = base.agg(F.sum(F.octet_length("text") + 1).alias("size"), F.sum((~F.col("held_out")).cast("long")).alias("trained")).first()
    trained = facts["trained"] or 0
    sums = counts.where("key < 0 AND n > 0").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).first()
    total, distinct = (sums["n"] or 0) + trained, (sums["v"] or 0) + (1 if trained else 0)

    grams = counts.where("key >= 0").select(F.col("key").alias("gram"), "n", F.shiftright("key", 8 * (depth + 1 - SHARD)).alias("shard"))
    size = counts.agg(F.count(F.lit(1)).alias("all"), F.count(F.when(F.col("key") >= 0, 1)).alias("grams")).first()
    # Ranges of contexts by sorting: contexts with the same latest bytes are in one partition, which numbers its rows.
    grams = written(grams.repartitionByRange(max(1, math.ceil(size["grams"] / RANGE_ROWS)), "shard").withColumn("range", F.spark_partition_id()), "lm-ranges")
    nodes = written(grams.where("n > 0").groupBy("range").applyInPandas(_range_nodes(depth), _NODES), "nodes-3")
    # A parent's children are together; one group holds the parents of a context without its oldest bytes.
    nodes = written(nodes.groupBy(F.pmod(F.xxhash64(F.shiftright("node", 16)), F.lit(64)).alias("g")).applyInPandas(_raise, _NODES), "nodes-2")
    first = nodes.groupBy(F.shiftright("node", 16).alias("g")).applyInPandas(_raise, _NODES).toPandas()
    first = _level(first)
    top = sent(docs.sparkSession, [raised(first.keys, first.zeros, first.ones, first.weighted), first])
    shards = max(1, math.ceil(size["all"] / SHARD_KEYS)) * 2 + 1  # odd, as the last byte of a context's key is a text's
    wanted = grams.select("range", F.shiftright("shard", 8).alias("context")).distinct()
    second = nodes.withColumn("context", F.shiftright("node", 8)).join(wanted, "context").select("range", "node", "zeros", "ones", "weighted")
    second = written(second, "nodes-asked")

    def answer(own: pd.DataFrame, above: pd.DataFrame) -> pd.DataFrame:
        codes = np.sort(own["gram"].to_numpy(np.int64))
        levels = build_levels(own["gram"].to_numpy(np.int64), own["n"].to_numpy(), depth, SHARD)
        second_, out = _level(above), [np.zeros(0)]
        for at in range(0, len(codes), 100_000):
            part = codes[at : at + 100_000]
            p = predict(opened(top), part, depth, 0, predict([second_], part, depth, 2, predict(levels, part, depth, SHARD)))
            out.append(np.log10(p).sum(axis=0))
        return pd.DataFrame(packed_by_shard(codes, np.concatenate(out), shards))

    def pack_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column("key").to_numpy()
            order = np.argsort(keys)
            made = packed_by_shard(keys[order], batch.column("n").to_numpy()[order].astype(float), shards)
            yield pa.RecordBatch.from_arrays([pa.array(made["shard"], pa.int64()), pa.array(made["packed"], pa.binary()), pa.array(made["value"], pa.binary())], names=["shard", "packed", "value"])

    kinds = "shard bigint, packed binary, value binary"
    model = grams.groupBy("range").cogroup(second.groupBy("range")).applyInPandas(answer, kinds)
    model = written(model.unionByName(counts.where("key < 0 AND n > 0").select("key", "n").mapInArrow(pack_words, kinds)), "lm-model")

    chunks = max(1, math.ceil((facts["size"] or 0) / chunk_bytes))
    dealt = base.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunks)))

    def ask(own: pa.Table) -> pa.Table:
        keys = distinct_keys(own.column("text"), depth)
        shard, chunk = keys % shards, own.column("chunk")[0].as_py()
        rows = [(chunk, k, keys[shard == k].tobytes()) for k in range(shards)]
        return pa.table({"chunk": pa.array([r[0] for r in rows], pa.int64()), "shard": pa.array([r[1] for r in rows], pa.int64()), "packed": pa.array([r[2] for r in rows], pa.binary())})

    def reply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows by shard, those of the model first: the shard is put together once and then asked row by row."""
        at, parts, own, value = None, [], np.zeros(0, np.int64), np.zeros(0)
        for batch in batches:
            for k in range(batch.num_rows):
                shard, chunk = batch.column("shard")[k].as_py(), batch.column("chunk")[k].as_py()
                packed = np.frombuffer(batch.column("packed")[k].as_buffer(), np.int64)
                if shard != at:
                    at, parts, own, value = shard, [], np.zeros(0, np.int64), np.zeros(0)
                if chunk < 0:
                    parts.append((packed.copy(), np.frombuffer(batch.column("value")[k].as_buffer(), float).copy()))
                    continue
                if parts:
                    own, value = (np.concatenate([p[x] for p in parts]) for x in (0, 1))
                    order = np.argsort(own)
                    own, value, parts = own[order], value[order], []
                found = np.minimum(np.searchsorted(own, packed), max(0, len(own) - 1))
                got = np.where(own[found] == packed, value[found], 0.0) if len(own) else np.zeros(len(packed))
                yield pa.RecordBatch.from_arrays([pa.array([chunk], pa.int64()), pa.array([shard], pa.int64()), pa.array([got.tobytes()], pa.binary())], names=["chunk", "shard", "packed"])

    asked = dealt.groupBy("chunk").applyInArrow(ask, "chunk bigint, shard bigint, packed binary").withColumn("value", F.lit(None).cast("binary"))
    stream = model.withColumn("chunk", F.lit(-1).cast("bigint")).unionByName(asked)
    answers = stream.repartition("shard").sortWithinPartitions("shard", "chunk").mapInArrow(reply, "chunk bigint, shard bigint, packed binary")
    kind = base.schema["doc_id"].dataType.simpleString()
    # The smoothed share of a token of count c is (c + 1) / (total + 1 * (distinct + 1)).
    log_all = math.log10(total + distinct + 1)
    log_end = math.log10(trained + 1) - log_all
    columns = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte"]

    def score(own: pa.Table, got: pa.Table) -> pa.Table:
        texts, n = own.column("text"), own.num_rows
        keys = distinct_keys(texts, depth)
        shard, value = keys % shards, np.zeros(len(keys))
        for k, packed in zip(got.column("shard").to_pylist(), got.column("packed")):
            value[shard == k] = np.frombuffer(packed.as_buffer(), float)
        model_log, base_log, n_tokens, n_known, sizes = np.zeros(n), np.full(n, log_end), np.ones(n, np.int64), np.full(n, int(trained > 0)), np.ones(n)
        for part in text_slices((t.as_py() for t in texts), depth):
            to, m = np.array(part.numbers), len(part.bodies)
            codes, lengths = gram_codes(part, depth)
            which, place, owner = grouped(codes, lengths, 8 * (depth + 1))
            np.add.at(model_log, to, np.bincount(owner, value[np.searchsorted(keys, which)][place], m))
            words, lengths = word_keys(part.bodies)
            which, place, owner = grouped(words, lengths, 64)
            c = value[np.searchsorted(keys, which)][place] if len(which) else np.zeros(0)
            np.add.at(base_log, to, np.bincount(owner, np.log10(c + 1), m) - lengths * log_all)
            np.add.at(n_known, to, np.bincount(owner, c > 0, m).astype(np.int64))
            np.add.at(n_tokens, to, lengths)
            np.add.at(sizes, to, [len(x) for x in part.bodies])
        made = [own.column("doc_id"), own.column("held_out"), pa.array(n_tokens), pa.array(n_known), pa.array(np.full(n, total, np.int64)), pa.array(base_log), pa.array(model_log), pa.array(-model_log / math.log10(2) / sizes)]
        return pa.table(dict(zip(columns, made)))

    schema = f"doc_id {kind}, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double, bits_per_byte double"
    return dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(score, schema)


def distinct_keys(texts: pa.ChunkedArray, depth: int) -> np.ndarray:
    """Sorted distinct keys of the contexts and words of texts, merged slice by slice."""
    out, waiting, size = np.zeros(0, np.int64), [], 0
    for part in text_slices((t.as_py() for t in texts), depth):
        waiting += [sorted_distinct(gram_codes(part, depth)[0])[0], sorted_distinct(word_keys(part.bodies)[0])[0]]
        size += len(waiting[-1]) + len(waiting[-2])
        if size > len(out) + 1_000_000:
            out, waiting, size = sorted_distinct(np.concatenate([out, *waiting]))[0], [], 0
    return sorted_distinct(np.concatenate([out, *waiting]))[0]


def packed_by_shard(keys: np.ndarray, values: np.ndarray, shards: int) -> dict[str, list]:
    """Keys and values of every shard that has any, as bytes."""
    shard = keys % shards
    order = np.argsort(shard, kind="stable")
    keys, values = keys[order], values[order]
    which, start = np.unique(shard[order], return_index=True)
    cuts = list(zip(start.tolist(), [*start[1:].tolist(), len(keys)]))
    return {"shard": which.tolist(), "packed": [keys[a:z].tobytes() for a, z in cuts], "value": [values[a:z].tobytes() for a, z in cuts]}
