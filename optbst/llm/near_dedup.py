"""Near-duplicate documents: fast similarity sketches, banding, exact verification, components.

A document's set holds its distinct shingles as 64-bit hashes. The sketch fills t bins in rounds:
in the first t rounds every shingle goes to one hashed bin with its round and a hashed fraction as
value; in the next t rounds round t+b sends every shingle to bin b, so that every bin is filled. The
coordinates agree with a probability equal to the similarity and concentrate as minwise hashing
does. Documents that agree in a band of coordinates are candidates; the estimate of the sketch
drops pairs that are far below the threshold, and full sets decide the rest.

Scale: exact copies (equal sets) are one class before anything is compared. In a bucket every class
is first compared with the bucket's smallest class only, so a bucket of m classes gives m - 1 pairs,
and the links found so join classes to components. A bucket whose classes are one component is
finished. In the others, classes outside the leader's component (the rest) are compared with all
classes of other components, in blocks of bounded size that are dealt to different tasks; a pair is
looked at only in the first bucket that it shares, sketch and size are compared before sets, and
only links leave a block. So no group of any size meets in one task, no pair list is written, and
no link between components is skipped. Joins are sort-merge joins on written tables, which Spark can
split when a key is hot.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import written
from .common import blank_words, map_batches, mix64, two_columns

_MULT = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], np.uint64)

#: Bytes of sets that a task of compared cells holds, about.
DEAL_BYTES = 32 << 20


def shingle_hashes(words: list[bytes], size: int, cache: dict[bytes, int]) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles; fewer words than ``size`` are one shingle, none give none."""
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) < size:
        return np.array([xxhash.xxh3_64_intdigest(b"\x00".join(words), seed=1)], np.uint64)
    for w in set(words).difference(cache):
        cache[w] = xxhash.xxh3_64_intdigest(w)
    h = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
    n = len(h) - size + 1
    acc = np.zeros(n, np.uint64)
    for k in range(size):
        acc = mix64(acc + h[k : k + n] * _MULT[k % 5])
    return np.unique(acc)


def similarity_sketch(hashes: np.ndarray, t: int) -> np.ndarray:
    """t coordinates (uint64: round in the high bits, hashed fraction below); ``hashes`` must not be empty."""
    out = np.full(t, np.iinfo(np.uint64).max, np.uint64)
    for r in range(2 * t):
        x = mix64(hashes + np.uint64((r + 1) * 0x9E3779B97F4A7C15 % (1 << 64)))
        value = (np.uint64(r) << np.uint64(48)) | (x >> np.uint64(16))
        if r < t:
            np.minimum.at(out, (x % np.uint64(t)).astype(np.int64), value)
        else:
            out[r - t] = min(out[r - t], value.min())
        # A later round has larger values only, so full bins are final.
        if (out != np.iinfo(np.uint64).max).all():
            break
    return out


def sketches(docs: DataFrame, shingle: int, bands: int, rows: int) -> DataFrame:
    """(doc_id, n_shingles, digest, keys, sketch) for each row of ``docs(doc_id, text)``; no words: null digest."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    t = bands * rows

    def make(batch: pa.RecordBatch) -> dict[str, object]:
        cache: dict[bytes, int] = {}
        n, digest, keys, sketch = [], [], [], []
        for text in batch.column("text").to_pylist():
            h = shingle_hashes(blank_words(text), shingle, cache)
            n.append(len(h))
            if not len(h):
                digest.append(None), keys.append(None), sketch.append(None)
                continue
            s = similarity_sketch(h, t)
            acc = np.arange(bands, dtype=np.uint64)
            for k in range(rows):
                acc = mix64(acc + s.reshape(bands, rows)[:, k] * _MULT[k % 5])
            digest.append(hashlib.blake2b(h.tobytes(), digest_size=16).digest())
            keys.append(acc.view(np.int64))
            sketch.append((mix64(s) & np.uint64(0x7FFF)).astype(np.int16))
        return {"doc_id": batch.column("doc_id"), "n_shingles": np.array(n, np.int64), "digest": digest, "keys": keys, "sketch": sketch}

    return map_batches(docs, f"doc_id {kind}, n_shingles bigint, digest binary, `keys` array<bigint>, sketch array<smallint>", make)


def shingle_sets(docs: DataFrame, shingle: int) -> DataFrame:
    """(doc_id, items): the full set of each row as sorted 64-bit integers."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def make(batch: pa.RecordBatch) -> dict[str, object]:
        cache: dict[bytes, int] = {}
        return {"doc_id": batch.column("doc_id"), "items": [shingle_hashes(blank_words(t), shingle, cache).view(np.int64) for t in batch.column("text").to_pylist()]}

    return map_batches(docs, f"doc_id {kind}, items array<bigint>", make)


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest node reachable over ``edges(a, b)``, for nodes that have an edge.

    Alternates hooking every neighbour to the smallest neighbour (large star) and every smaller
    neighbour to it (small star) until nothing changes; a written table ends each round.
    """
    e = written(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    for _ in range(most_rounds):
        both = e.select("u", "v").unionAll(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = written(both.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("m")), "star")
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = written(large, "large-star")
        low = written(large.groupBy("u").agg(F.min("v").alias("m")), "star")
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(low.select("u", F.col("m").alias("v")))
        small = written(small.where("u <> v").distinct(), "small-star")
        changed = small.exceptAll(e).take(1) or e.exceptAll(small).take(1)
        e = small
        if not changed:
            break
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionAll(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def near_duplicates(
    docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 5, percent: int = 80, bands: int = 20, rows: int = 4, slack: float = 0.25
) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id, kept, n_class.

    Rows are linked when 100 * |intersection| >= percent * |union| of their full sets of ``shingle``
    words. component_id is the smallest doc_id that links reach. Null, empty and blank texts have no
    set and are alone. A null doc_id takes part only as an exact copy or alone (its component is that
    of its copies, else null). Rows that repeat a doc_id share its component and kept.

    A pair at similarity s is a candidate with probability 1 - (1 - s^rows)^bands; with 20 bands of 4
    a pair at 0.85 is missed once in two million, a pair at 0.8 once in thirty thousand. ``slack`` is
    how far below the threshold the sketch's estimate may be before the pair is not verified (over
    five standard deviations of 80 coordinates).
    """
    base = two_columns(docs, key, text)
    facts = written(sketches(base, shingle, bands, rows), "sketches")
    # A null id never wins the minimum, so a class of ids has a real one as its name.
    classes = facts.where("digest IS NOT NULL AND doc_id IS NOT NULL").groupBy("digest").agg(
        F.min(F.struct("doc_id", "n_shingles", "keys", "sketch")).alias("x"), F.count(F.lit(1)).alias("n_class")
    )
    classes = written(classes.select("digest", "n_class", F.col("x.doc_id").alias("rep"), F.col("x.n_shingles").alias("n"), F.col("x.keys").alias("keys"), F.col("x.sketch").alias("sketch")), "classes")
    spread = classes.select("rep", "n", F.posexplode("keys").alias("band", "key")).select("rep", "n", "band", F.xxhash64("band", "key").alias("bucket"))
    leaders = written(spread.groupBy("bucket").agg(F.min("rep").alias("leader"), F.count(F.lit(1)).alias("m")).where("m > 1"), "leaders")
    members = written(spread.join(leaders.select("bucket", "leader"), "bucket"), "members")
    # One text pass for the sets of all classes that share a bucket with another.
    sets = shingle_sets(base.join(members.select(F.col("rep").alias("doc_id")).distinct(), "doc_id", "left_semi"), shingle)
    sets = written(sets.groupBy("doc_id").agg(F.max("items").alias("items")), "sets")
    edges = leader_links(classes, members, sets, percent, slack)
    edges = edges.unionAll(block_links(classes, members, sets, edges, percent, slack))
    found = components(edges)
    named = classes.select("digest", "rep", "n_class").join(found, F.col("rep") == F.col("node"), "left").select("digest", "n_class", F.coalesce("component", "rep").alias("component_id"))
    named = written(named, "named")
    out = facts.select("doc_id", "n_shingles", "digest").join(named, "digest", "left")
    return out.select(
        "doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"),
        F.coalesce(F.col("doc_id") == F.coalesce("component_id", "doc_id"), F.lit(True)).alias("kept"),
        F.coalesce("n_class", F.lit(1)).alias("n_class"),
    )


def leader_links(classes: DataFrame, members: DataFrame, sets: DataFrame, percent: int, slack: float) -> DataFrame:
    """Links (a, b) of classes with the leaders of their buckets, from full sets."""
    pairs = members.where("rep <> leader").select(F.col("leader").alias("a"), F.col("rep").alias("b")).distinct()
    small = classes.select("rep", "n", "sketch")
    near = pairs.join(small.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb")), "b").join(
        small.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa")), "a"
    )
    equal = F.aggregate(F.zip_with("sa", "sb", lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    near = near.where((100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & (equal >= (percent / 100 - slack) * F.size("sa")))
    near = written(near.select("a", "b", "na", "nb"), "near-pairs")
    both = near.join(sets.select(F.col("doc_id").alias("b"), F.col("items").alias("ib")), "b").join(sets.select(F.col("doc_id").alias("a"), F.col("items").alias("ia")), "a")
    both = both.select("a", "b", "na", "nb", F.size(F.array_intersect("ia", "ib")).cast("long").alias("inter"))
    return written(both.where(100 * F.col("inter") >= percent * (F.col("na") + F.col("nb") - F.col("inter"))).select("a", "b"), "leader-links")


def block_links(
    classes: DataFrame, members: DataFrame, sets: DataFrame, edges: DataFrame, percent: int, slack: float, block_classes: int = 256, block_shingles: int = 1_000_000
) -> DataFrame:
    """Links (a, b) between classes of one bucket that ``edges`` leave in different components.

    Of several links that join the same two components inside one block, one may stand for the rest.
    """
    kind = classes.schema["rep"].dataType.simpleString()
    label = written(components(edges).distinct(), "labels")
    tagged = members.join(label.withColumnRenamed("node", "rep"), "rep", "left").select("bucket", "band", "leader", "rep", "n", F.coalesce("component", "rep").alias("comp"))
    tagged = written(tagged, "tagged")
    core = tagged.where("rep = leader").select("bucket", F.col("comp").alias("core"))
    open_ = tagged.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("bucket").join(core, "bucket")
    split = written(tagged.join(written(open_, "open"), "bucket").withColumn("rest", F.col("comp") != F.col("core")), "split")
    cuts = lambda which: F.ceil(F.greatest(F.sum(which.cast("long")) / block_classes, F.sum(F.when(which, F.col("n")).otherwise(0)) / block_shingles)).cast("int")
    counts = written(split.groupBy("bucket").agg(cuts(F.col("rest")).alias("n_rest"), cuts(~F.col("rest")).alias("n_core")), "cuts")
    own = F.pmod(F.xxhash64("rep"), F.when(F.col("rest"), F.col("n_rest")).otherwise(F.col("n_core"))).cast("int")
    # A block is a chunk of the rest (x) against a chunk of the core (y < 0) or a chunk of the rest (y >= x).
    cells = F.when(~F.col("rest"), F.expr("transform(sequence(0, n_rest - 1), x -> struct(x AS x, -1 - own AS y))")).otherwise(
        F.expr("concat(transform(sequence(0, n_rest - 1), o -> struct(least(o, own) AS x, greatest(o, own) AS y)), transform(sequence(1, n_core), c -> struct(own AS x, -c AS y)))")
    )
    cells = split.join(counts, "bucket").withColumn("own", own).select("bucket", "band", "rep", "comp", "n", "rest", F.explode(cells).alias("cell"))
    cells = written(cells, "cells")
    data = sets.select(F.col("doc_id").alias("rep"), "items").join(classes.select("rep", "sketch", "keys"), "rep")
    # Most cells are tiny: a task takes a share of them, some thousand rows and some ten megabytes of sets.
    facts = cells.agg(F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum("n"), F.lit(0)).alias("items")).first()
    deals = max(1, facts["rows"] // 2000, 8 * facts["items"] // DEAL_BYTES)
    full = cells.join(written(data, "block-data"), "rep").withColumn("deal", F.pmod(F.xxhash64("bucket", "cell"), F.lit(deals)))

    def links(pdf):  # noqa: ANN001, ANN202
        import pandas as pd

        out: list[tuple] = []
        place = np.stack([pdf["bucket"].to_numpy(), pdf["cell"].map(lambda c: c["x"]).to_numpy(np.int64), pdf["cell"].map(lambda c: c["y"]).to_numpy(np.int64)])
        order = np.lexsort(place)
        place = place[:, order]
        starts = np.flatnonzero(np.concatenate([[True], (place[:, 1:] != place[:, :-1]).any(axis=0)])).tolist() + [len(order)]
        columns = {c: pdf[c].to_numpy()[order] for c in ("sketch", "keys", "n", "comp", "rest", "rep", "items", "band")}
        for at, end in zip(starts, starts[1:]):
            own = {c: v[at:end] for c, v in columns.items()}
            if own["rest"].any() and end - at > 1:
                out += _cell_links(**own, percent=percent, slack=slack)
        return pd.DataFrame({"a": [a for a, _ in out], "b": [b for _, b in out]}).astype({"a": pdf["rep"].dtype, "b": pdf["rep"].dtype})

    return written(full.groupBy("deal").applyInPandas(links, f"a {kind}, b {kind}"), "block-links")


def _cell_links(sketch, keys, n, comp, rest, rep, items, band, percent: int, slack: float) -> list[tuple]:  # noqa: ANN001
    """Links between classes of different components in one cell; those that are not core come first in a pair."""
    out, joined = [], set()
    sk, bands, numbers = np.stack(sketch), np.stack(keys), np.arange(len(n))
    for p in np.flatnonzero(rest):
        q = np.flatnonzero((comp != comp[p]) & (~rest | (numbers > p)))
        q = q[100 * np.minimum(n[q], n[p]) >= percent * np.maximum(n[q], n[p])]
        if not len(q):
            continue
        q = q[(sk[q] == sk[p]).mean(axis=1) >= percent / 100 - slack]
        # Only in the first band that the two share is the pair looked at. The keys decide, as buckets are made from them.
        q = q[(bands[q] == bands[p]).argmax(axis=1) >= band[0]]
        for o in q:
            if (comp[p], comp[o]) in joined:
                continue
            inter = len(np.intersect1d(items[p], items[o], assume_unique=True))
            if 100 * inter >= percent * (n[p] + n[o] - inter):
                joined |= {(comp[p], comp[o]), (comp[o], comp[p])}
                out.append((rep[p], rep[o]))
    return out
