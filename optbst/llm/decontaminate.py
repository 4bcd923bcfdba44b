"""Benchmark decontamination with a distributed positional inverted index.

``build_index`` stores the postings of all document words as a table: a row is a segment of the index, the
sorted terms of some documents, how often each stands there and at which places. A segment belongs to its
documents, so a term that a third of all documents share is spread over all segments. Benchmark windows
are looked up from their rarest terms: the places of a window's rarest term, moved by its offset in the
window, are intersected with the moved lists of its other terms in order of corpus-wide rarity until the
places that are left are exact phrase matches. Proximity matches come from the same lists.

Scale: one pass over the texts writes the index, texts are never shuffled. Rarity is counted from two of
the index's columns. The benchmark is the stated query set: it is read to the driver in blocks of at most
``block_words`` words, as arrays of numbers of a bounded size, and each block is one pass over the index.
Only documents with matches leave a pass; they are merged by segment and place in it, in one plan
whatever the number of blocks. Terms are 63-bit hashes of words; a false match needs a word with the hash
of another in the midst of an otherwise equal phrase.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..storage import written
from .common import alnum_bytes, sliced, two_columns, word_keys

WINDOW = 13
#: Words of a benchmark block: some fifty bytes each on the driver and in each worker.
BLOCK_WORDS = 1_000_000
#: Text bytes of a segment of the index, about; a longer text is a segment of its own.
SEGMENT_BYTES = 2 << 20
#: Proximity: an item's rarest terms, within so many words.
RARE_TERMS, WITHIN = 4, 20


def build_index(docs: DataFrame, key: str = "doc_id", text: str = "text", segment_bytes: int = SEGMENT_BYTES) -> DataFrame:
    """The positional index as a written table (segment, ids, n_words, terms, counts, places).

    ``ids`` and ``n_words`` are those of the segment's documents, in order; ``terms`` are sorted 64-bit
    integers, ``counts`` and ``places`` 32-bit ones, all as bytes. Places count the words of the segment from 0.
    """
    base = two_columns(docs, key, text)
    kind = base.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for batch in batches:
            for part in sliced(batch, segment_bytes):
                keys, lengths = word_keys([alnum_bytes(t.as_py()) for t in part.column("text")])
                order = np.argsort(keys, kind="stable")
                keys = keys[order]
                first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
                count = np.diff(np.append(first, len(keys))).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([number], pa.int64()), pa.ListArray.from_arrays(pa.array([0, len(lengths)], pa.int32()), part.column("doc_id")),
                        pa.array([lengths], pa.list_(pa.int64())), pa.array([keys[first].tobytes()], pa.binary()), pa.array([count.tobytes()], pa.binary()), pa.array([order.astype(np.int32).tobytes()], pa.binary()),
                    ],
                    names=["segment", "ids", "n_words", "terms", "counts", "places"],
                )
                number += 1

    # Rows are some megabytes, so row groups are kept small: a reader holds one.
    return written(base.mapInArrow(run, f"segment bigint, ids array<{kind}>, n_words array<bigint>, terms binary, counts binary, places binary"), "postings", options={"parquet.block.size": 4 * segment_bytes, "parquet.enable.dictionary": False})


@dataclass
class Queries:
    """Windows of some benchmark items over their vocabulary, as arrays."""

    item_ids: list[str]
    terms: np.ndarray  # sorted distinct hashes
    #: term numbers of each item
    items: list[np.ndarray]
    #: (windows as rows of term numbers, where each one's owners begin, owners)
    groups: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)
    #: columns of the windows of each group from the rarest term on
    rarity: list[np.ndarray] = field(default_factory=list)
    #: the rarest terms of each item
    near: list[np.ndarray] = field(default_factory=list)


def make_queries(item_ids: list[str], texts: list[bytes], window: int) -> Queries:
    """Distinct windows of items; an item of fewer words, but not none, is one window."""
    keys, lengths = word_keys(texts)
    terms, codes = np.unique(keys, return_inverse=True)
    items = np.split(codes.astype(np.int32), np.cumsum(lengths)[:-1]) if len(lengths) else []
    out = Queries(item_ids, terms, items)
    for width in sorted({min(window, len(x)) for x in items if len(x)}):
        own = [k for k, x in enumerate(items) if min(window, len(x)) == width]
        rows = np.concatenate([np.lib.stride_tricks.sliding_window_view(items[k], width) for k in own])
        owner = np.repeat(own, [len(items[k]) - width + 1 for k in own])
        windows, which = np.unique(rows, axis=0, return_inverse=True)
        pairs = np.unique(np.stack([which.ravel(), owner], axis=1), axis=0)
        out.groups.append((windows, np.searchsorted(pairs[:, 0], np.arange(len(windows) + 1)), pairs[:, 1].astype(np.int32)))
    return out


def rank_terms(queries: Queries, counts: np.ndarray, rare_terms: int) -> None:
    """Order every window's columns, and choose every item's terms, by how often terms stand in all documents."""
    queries.rarity = [np.argsort(counts[windows], axis=1, kind="stable").astype(np.int8 if windows.shape[1] < 128 else np.int32) for windows, _, _ in queries.groups]
    for codes in queries.items:
        distinct, first = np.unique(codes, return_index=True)
        queries.near.append(distinct[np.lexsort((first, counts[distinct]))][:rare_terms])


class Segment:
    """The lists of a segment for the terms of a vocabulary, as one sorted array of (term number, place)."""

    def __init__(self, row: dict, vocabulary: np.ndarray):
        terms, counts, places = (np.frombuffer(row[c], t) for c, t in (("terms", np.int64), ("counts", np.int32), ("places", np.int32)))
        self.first = np.concatenate([[0], np.cumsum(row["n_words"])]).astype(np.int64)
        at = np.minimum(np.searchsorted(terms, vocabulary), max(0, len(terms) - 1))
        here = terms[at] == vocabulary if len(terms) else np.zeros(len(vocabulary), bool)
        self.count = np.where(here, counts[at], 0).astype(np.int64) if len(terms) else np.zeros(len(vocabulary), np.int64)
        self.start = np.concatenate([[0], np.cumsum(self.count)])
        begin = (np.cumsum(counts, dtype=np.int64) - counts)[at] if len(terms) else at
        own = np.repeat(np.arange(len(vocabulary), dtype=np.int64), self.count)
        self.keys = (own << 32) | places[np.arange(self.start[-1]) + (begin - self.start[:-1])[own]]

    def places(self, term: int) -> np.ndarray:
        return self.keys[self.start[term] : self.start[term + 1]] & 0xFFFFFFFF

    def document(self, places: np.ndarray) -> np.ndarray:
        """The document, by its place in the segment, of each word."""
        return np.searchsorted(self.first[:-1], places, side="right") - 1

    def phrases(self, windows: np.ndarray, rarity: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(window number, place of its first word) of every exact occurrence inside one document."""
        width = windows.shape[1]
        number = np.flatnonzero((self.count[windows] > 0).all(axis=1))
        column = rarity[number, 0].astype(np.int64)
        term = windows[number, column]
        n = self.count[term]
        place = self.keys[np.arange(n.sum()) + np.repeat(self.start[term] - np.cumsum(n) + n, n)] & 0xFFFFFFFF
        number, place = np.repeat(number, n), place - np.repeat(column, n)
        keep = place >= 0
        number, place = number[keep], place[keep]
        for k in range(1, width):  # the list of the next rarest term, moved by its offset
            if not len(number):
                break
            column = rarity[number, k].astype(np.int64)
            wanted = (windows[number, column].astype(np.int64) << 32) | (place + column)
            keep = self.keys[np.minimum(np.searchsorted(self.keys, wanted), len(self.keys) - 1)] == wanted
            number, place = number[keep], place[keep]
        keep = self.document(place) == self.document(place + width - 1)
        return number[keep], place[keep]

    def near(self, terms: np.ndarray, within: int) -> list[tuple[int, int]]:
        """Smallest stretches (first word, end) of at most ``within`` words of a document that hold all of the distinct ``terms``."""
        lists = [self.places(t) for t in terms]
        ends = np.sort(np.concatenate(lists))
        # The latest place of every term up to each end: the stretch that ends there starts at the earliest of them.
        at = np.stack([np.searchsorted(own, ends, side="right") - 1 for own in lists])
        starts = np.stack([own[np.maximum(k, 0)] for own, k in zip(lists, at)]).min(axis=0)
        keep = (at >= 0).all(axis=0) & (ends - starts < within) & (self.document(starts) == self.document(ends))
        starts, ends = starts[keep], ends[keep]
        first = np.concatenate([[True], starts[1:] != starts[:-1]]) if len(starts) else keep[:0]  # the smallest end of each start
        return [(int(x), int(y) + 1) for x, y in zip(starts[first], ends[first])]


def benchmark_blocks(benchmark: DataFrame, key: str, text: str, block_words: int) -> Iterator[tuple[list[str], list[bytes]]]:
    """Item ids and texts, as bytes of words between blanks, in blocks of at most ``block_words`` words (an item is never cut)."""
    ids, texts, words = [], [], 0
    for row in two_columns(benchmark, key, text).toLocalIterator():
        own = alnum_bytes(row["text"])
        n = len(own.split())
        if texts and words + n > block_words:
            yield ids, texts
            ids, texts, words = [], [], 0
        ids.append("" if row["doc_id"] is None else str(row["doc_id"]))
        texts.append(own)
        words += n
    if texts:
        yield ids, texts


def term_counts(index: DataFrame, terms: np.ndarray) -> np.ndarray:
    """How often each of some sorted terms stands in all documents; a task sends one row a term that it saw."""
    asked = sent(index.sparkSession, terms)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = opened(asked)
        total = np.zeros(len(wanted), np.int64)
        for batch in batches:
            for row in range(batch.num_rows):
                own, n = np.frombuffer(batch.column("terms")[row].as_buffer(), np.int64), np.frombuffer(batch.column("counts")[row].as_buffer(), np.int32)
                at = np.searchsorted(wanted, own)
                known = np.flatnonzero(wanted[np.minimum(at, len(wanted) - 1)] == own) if len(wanted) else at[:0]
                total[at[known]] += n[known]
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(total[seen], pa.int64())], names=["term", "n"])

    out = np.zeros(len(terms), np.int64)
    for row in index.select("terms", "counts").mapInArrow(run, "term bigint, n bigint").groupBy("term").agg(F.sum("n").alias("n")).collect():  # at most a block's terms
        out[row["term"]] = row["n"]
    return out


_SPAN = pa.struct([("first", pa.int64()), ("end", pa.int64())])
_NEAR = pa.struct([("item", pa.string()), ("first", pa.int64()), ("end", pa.int64())])
_FOUND = "segment bigint, at bigint, spans array<struct<first: bigint, `end`: bigint>>, items array<string>, near array<struct<item: string, first: bigint, `end`: bigint>>"


def matches(index: DataFrame, queries: Queries, within: int) -> DataFrame:
    """(segment, at, spans, items, near) of the documents of an index that have a match of some items."""
    asked = sent(index.sparkSession, queries)

    def found(segment: Segment, q: Queries) -> Iterator[tuple[int, list, list, list]]:
        spans, items, near = {}, {}, {}
        covers = np.zeros(int(segment.first[-1]) + 1, np.int32)
        for (windows, start, owners), rarity in zip(q.groups, q.rarity):
            number, place = segment.phrases(windows, rarity)
            np.add.at(covers, place, 1)
            np.add.at(covers, place + windows.shape[1], -1)
            # Items by document: each (document, window) once.
            for d, w in np.unique(np.stack([segment.document(place), number], axis=1), axis=0).tolist():
                items.setdefault(d, set()).update(owners[start[w] : start[w + 1]].tolist())
        # A stretch ends with its document, also where the next word is covered too.
        depth = np.cumsum(covers[:-1]) > 0
        begins = np.zeros(len(depth) + 1, bool)
        begins[segment.first] = True
        inside = np.flatnonzero(depth)
        if len(inside):
            new = np.concatenate([[True], (inside[1:] != inside[:-1] + 1) | begins[inside[1:]]])
            edges = np.append(np.flatnonzero(new), len(inside))
            for a, z in zip(inside[edges[:-1]].tolist(), (inside[edges[1:] - 1] + 1).tolist()):
                d = int(segment.document(np.array(a)))
                spans.setdefault(d, []).append({"first": a - int(segment.first[d]), "end": z - int(segment.first[d])})
        for k, terms in enumerate(q.near):
            if len(terms) and (segment.count[terms] > 0).all():
                for a, z in segment.near(terms, within):
                    d = int(segment.document(np.array(a)))
                    near.setdefault(d, []).append({"item": q.item_ids[k], "first": a - int(segment.first[d]), "end": z - int(segment.first[d])})
        for d in sorted(items.keys() | near.keys()):
            yield d, spans.get(d, []), sorted({q.item_ids[k] for k in items.get(d, ())}), near.get(d, [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = opened(asked)
        for batch in batches:
            for k in range(batch.num_rows):
                row = {c: batch.column(c)[k].as_buffer() for c in ("terms", "counts", "places")} | {"n_words": batch.column("n_words")[k].values.to_numpy()}
                rows = list(found(Segment(row, q.terms), q))
                number = batch.column("segment")[k].as_py()
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([number] * len(rows), pa.int64()), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.list_(_SPAN)),
                        pa.array([r[2] for r in rows], pa.list_(pa.string())), pa.array([r[3] for r in rows], pa.list_(_NEAR)),
                    ],
                    names=["segment", "at", "spans", "items", "near"],
                )

    return index.select("segment", "n_words", "terms", "counts", "places").mapInArrow(run, _FOUND)


#: Overlapping or touching stretches of sorted ``spans`` become one.
_MERGE = """aggregate(spans, cast(array() AS array<struct<first: bigint, end: bigint>>), (a, s) ->
 IF(size(a) > 0 AND element_at(a, -1).end >= s.first,
    concat(slice(a, 1, size(a) - 1), array(struct(element_at(a, -1).first AS first, greatest(element_at(a, -1).end, s.end) AS end))), concat(a, array(s))))"""


def contamination(
    docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", window: int = WINDOW, block_words: int = BLOCK_WORDS,
    rare_terms: int = RARE_TERMS, within: int = WITHIN,
) -> DataFrame:
    """One row per input row: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, n_near, items, spans, near.

    A word inside any occurrence of a window is hit. Items with equal ids count once. ``spans`` are the
    hit stretches (first word, end). ``near`` has the proximity matches (item, first word, end): smallest
    stretches of at most ``within`` words that hold the item's ``rare_terms`` rarest distinct terms (all of
    them if it has fewer; rarity is the number of places in all documents, ties go to the term that comes
    first in the item); ``n_near`` counts their items. Null and empty texts have no words and are clean;
    null item ids are left out of the id list as empty text; an empty benchmark gives no hits; repeated
    rows are judged alike.
    """
    index = build_index(docs, key, text)
    found = []
    for ids, texts in benchmark_blocks(benchmark, item_key, item_text, block_words):  # the driver holds one block at a time
        queries = make_queries(ids, texts, window)
        rank_terms(queries, term_counts(index, queries.terms), rare_terms)
        found.append(matches(index, queries, within))
    if not found:
        found = [docs.sparkSession.createDataFrame([], _FOUND)]
    merged = reduce(DataFrame.unionByName, found).groupBy("segment", "at").agg(
        F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("near")))).alias("near"),
    )
    rows = index.select("segment", F.posexplode(F.arrays_zip("ids", "n_words")).alias("at", "d")).select("segment", F.col("at").cast("bigint").alias("at"), F.col("d.ids").alias("doc_id"), F.col("d.n_words").alias("n_words"))
    empty = lambda c, t: F.coalesce(c, F.expr(f"cast(array() AS {t})"))
    rows = rows.join(merged, ["segment", "at"], "left").select(
        "doc_id", "n_words", empty(F.expr(_MERGE), "array<struct<first: bigint, `end`: bigint>>").alias("spans"), empty(F.col("items"), "array<string>").alias("items"),
        empty(F.col("near"), "array<struct<item: string, first: bigint, `end`: bigint>>").alias("near"),
    )
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["first"])
    return rows.select("*", hit.alias("n_hit")).select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
        F.size(F.array_distinct(F.transform("near", lambda x: x["item"]))).cast("long").alias("n_near"),
        "items",
        "spans",
        "near",
    )


def proximity_matches(
    docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", rare_terms: int = RARE_TERMS, within: int = WITHIN
) -> DataFrame:
    """(doc_id, item, first, end): the proximity matches of ``contamination``, one a row."""
    found = contamination(docs, benchmark, key, text, item_key, item_text, rare_terms=rare_terms, within=within)
    return found.select("doc_id", F.explode("near").alias("x")).select("doc_id", "x.item", "x.first", "x.end")
