"""Best-fit packing of tokenised documents into sequences by hierarchical residual packing.

Each partition of documents is tokenised and packed by best fit, longest pieces first. Bins that are
nearly full leave at once. Underfull bins become the items of the next level, where a few nodes meet
and best fit runs again, up to one root.

Scale: texts are never shuffled; a partition holds only the lengths of its pieces. What moves up a
level are all underfull bins, which best fit leaves few of; where they are many, a level has as many
nodes as it takes to give each about ``node_bins`` of them, so no node grows with the data. Tokenising
looks each distinct piece between blanks and marks up once for a worker's cache, where the tokenizer
file's own steps part texts there; this is read from the file, and other files encode whole texts.
"""

from __future__ import annotations

import bisect
import json
import math
import os
import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..storage import written
from .common import sliced, two_columns

SEQUENCE = 4096
END_ID = 1


def best_fit(sizes: Iterable[int], capacity: int) -> list[list[int]]:
    """Bins of item numbers by best fit decreasing; ties of equal size keep the given order."""
    sizes = list(sizes)
    by_free: dict[int, list[int]] = {}
    frees: list[int] = []
    bins: list[list[int]] = []

    def put(free: int, b: int) -> None:
        if free not in by_free or not by_free[free]:
            if free not in by_free:
                by_free[free] = []
            bisect.insort(frees, free)
        by_free[free].append(b)

    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        at = bisect.bisect_left(frees, sizes[i])
        if at == len(frees):
            bins.append([i])
            put(capacity - sizes[i], len(bins) - 1)
            continue
        free = frees[at]
        b = by_free[free].pop()
        if not by_free[free]:
            frees.pop(at)
        bins[b].append(i)
        put(free - sizes[i], b)
    return bins


#: Characters that the word tokenizer takes for letters, lower-cases one by one and never composes with others.
_LETTERS = r"A-Za-z\xC0-\xD6\xD8-\xF6\xF8-\xFF"
_STEM = re.compile(f"[{_LETTERS}]+")
#: ASCII marks but the apostrophe, as an RE2 class: a run of them is a piece of its own ...
_MARK = r"[!-&(-/:-@\[-`{-~]"
#: ... unless it touches an apostrophe (contractions) or a character that may belong to the run; letters of these ranges do not.
_JOINS = r"[^\x09-\x0D\x20-\x26\x28-\x7EÀ-ÖØ-öø-įı-ɏΑ-ΡΣ-ωА-яぁ-ゖァ-ヺ一-龥가-힣]"

# The steps of the tokenizer files for which texts may be parted before they are encoded.
_PARTED_NORMALIZER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
_PARTED_PRETOKENIZER = [
    {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True},
    {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
]


def parts_at_blanks(content: str) -> bool:
    """Whether this tokenizer file's steps allow encoding the pieces between blanks and marks alone.

    It must lower-case, drop white space, split letters from marks and end each piece of letters with an
    id of its own kind; no special token may stand in ordinary text as several pieces.
    """
    own = json.loads(content)
    model, norm, pre = own.get("model") or {}, own.get("normalizer") or {}, own.get("pre_tokenizer") or {}
    plain = norm.get("normalizers") == _PARTED_NORMALIZER and pre.get("pretokenizers") == _PARTED_PRETOKENIZER
    alone = not any(model.get(k) for k in ("dropout", "unk_token", "fuse_unk", "byte_fallback", "ignore_merges", "continuing_subword_prefix"))
    return plain and alone and model.get("type") == "BPE" and model.get("end_of_word_suffix") == "</w>" and not own.get("truncation") and not own.get("padding")


class RunTokenizer:
    """Ids of texts by a tokenizer file's content.

    Where the file's steps allow it, texts are parted at blanks and around marks in Arrow, and each distinct
    piece is encoded once and remembered; other files encode whole texts. Pickles as the content only;
    a worker process keeps one for all of its tasks.
    """

    def __init__(self, content: str, most_pieces: int = 600_000):
        self.content, self.most, self.own = content, most_pieces, None

    def __getstate__(self) -> dict:
        return {"content": self.content, "most": self.most, "own": None}

    def _open(self) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.own, self.cache = Tokenizer.from_str(self.content), {"": b""}
        self.parted = parts_at_blanks(self.content)
        content = json.loads(self.content)
        if self.parted:
            vocabulary = content["model"]["vocab"]
            self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
            self.ends[[i for w, i in vocabulary.items() if w.endswith("</w>")]] = True
            self.special = [t["content"] for t in content.get("added_tokens") or []]

    def _learn(self, pieces: list[str]) -> None:
        stems = [w for w in pieces if _STEM.fullmatch(w)]
        alone = list(set(pieces).difference(stems))
        for w, e in zip(alone, self.own.encode_batch_fast(alone, add_special_tokens=False)):
            self.cache[w] = np.array(e.ids, "<u4").tobytes()
        # Several pieces of letters as one text: each ends with the first id that ends a word.
        joined = [" ".join(stems[at : at + 256]) for at in range(0, len(stems), 256)]
        for at in range(0, len(joined), 64):
            ids = np.array([i for e in self.own.encode_batch_fast(joined[at : at + 64], add_special_tokens=False) for i in e.ids], "<u4")
            last = 4 * (np.flatnonzero(self.ends[ids]) + 1)
            own, raw = stems[at * 256 : (at + 64) * 256], ids.tobytes()
            if len(last) != len(own):
                raise ValueError("the tokenizer does not end every word with an id of its own kind")
            self.cache.update((w, raw[a:z]) for w, a, z in zip(own, [0, *last.tolist()], last.tolist()))

    def _whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.own.encode_batch_fast(texts, add_special_tokens=False)]

    def ids(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(unsigned 32-bit ids of all texts in a row, where each text's ids end)."""
        if self.own is None:
            self._open()
        texts = texts.fill_null("")
        if not self.parted:
            found = self._whole(texts.to_pylist())
            return np.array([i for x in found for i in x], "<u4"), np.cumsum([len(x) for x in found], dtype=np.int64)
        if len(self.cache) > self.most:
            self.cache = {"": b""}
        plain = pc.replace_substring(pc.ascii_lower(texts), "\n", " ")
        # Strings of special tokens are cut out before anything else, so texts that hold one are encoded whole.
        special = np.zeros(len(texts), bool)
        for token in self.special:
            special |= pc.or_(pc.match_substring(texts, token), pc.match_substring(plain, token)).to_numpy(False)
        if special.any():
            plain = pc.if_else(pa.array(special), pa.scalar(""), plain)
        odd = pc.match_substring_regex(plain, f"{_MARK}{_JOINS}|{_JOINS}{_MARK}")
        apart = pc.replace_substring_regex(plain, f"({_MARK}+)", r" \1 ")
        lists = pc.split_pattern(pc.if_else(odd, plain, apart), " ")
        out, ends = self._coded(lists.flatten())
        ends = np.concatenate([[0], ends])[lists.offsets.to_numpy()[1:] - lists.offsets[0].as_py()]
        if special.any():
            own = np.split(out, ends[:-1])
            for at in np.flatnonzero(special).tolist():
                own[at] = np.array(self._whole([texts[at].as_py()])[0], "<u4")
            out, ends = np.concatenate(own), np.cumsum([len(x) for x in own])
        return out, ends

    def _coded(self, pieces: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all pieces in a row, where each piece's ids end."""
        coded = pieces.dictionary_encode()
        distinct = coded.dictionary.to_pylist()
        new = [w for w in distinct if w not in self.cache]
        if new:
            self._learn(new)
        known = [self.cache[w] for w in distinct]
        size = np.fromiter(map(len, known), np.int64, len(known)) >> 2
        first, place = np.cumsum(size) - size, coded.indices.to_numpy()
        count = size[place]
        ends = np.cumsum(count)
        if not len(ends) or not ends[-1]:
            return np.zeros(0, "<u4"), ends
        return np.frombuffer(b"".join(known), "<u4")[np.arange(ends[-1]) + np.repeat(first[place] - ends + count, count)], ends


def tokenizer_content(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def best_fit_packing(docs: DataFrame, tokenizer: str, key: str = "doc_id", text: str = "text", capacity: int = SEQUENCE, end_id: int = END_ID, nearly_full: int = 8, fan_in: int = 8, node_bins: int = 20_000) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    A document is its ids and then ``end_id``, so a null or empty text is one piece of length 1. Only
    documents longer than ``capacity`` are cut, into full pieces and a last one. Bins with at most
    ``nearly_full`` free places leave at their level; all others go up, until one node holds them or a
    round of best fit no longer lowers their number. Repeated rows are packed each for itself, null keys
    stay null; an empty table gives no rows. ``tokenizer`` is the path of a tokenizer file; the driver reads it.
    """
    base = two_columns(docs, key, text)
    kind = base.schema["doc_id"].dataType
    tokens = sent(docs.sparkSession, RunTokenizer(tokenizer_content(tokenizer)))
    member = f"struct<doc_id: {kind.simpleString()}, piece: int, start: bigint, length: bigint, ids_crc32: bigint, `offset`: bigint>"
    schema = f"level int, node bigint, bin bigint, fill bigint, closed boolean, members array<{member}>"

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, end = opened(tokens), np.array([end_id], "<u4").tobytes()
        keys, rows, numbers, starts, lengths, sums = [], [], [], [], [], []
        for batch in batches:
            for part in sliced(batch, 8 << 20):
                ids, ends = own.ids(part.column("text"))
                raw, first = ids.tobytes(), 0
                for row, last in enumerate((4 * ends).tolist()):
                    own_ids, first = raw[first:last] + end, last
                    for n, at in enumerate(range(0, len(own_ids), 4 * capacity)):
                        piece = own_ids[at : at + 4 * capacity]
                        rows.append(row), numbers.append(n), starts.append(at // 4), lengths.append(len(piece) // 4), sums.append(zlib.crc32(piece))
                keys.append(part.column("doc_id").take(pa.array(rows, pa.int64())))
                rows.clear()
        if not lengths:
            return
        keys = pa.concat_arrays(keys)
        bins = best_fit(lengths, capacity)
        order = np.array([i for b in bins for i in b], np.int64)
        size, counts = np.array(lengths, np.int64), np.array([len(b) for b in bins], np.int64)
        edges = np.concatenate([[0], np.cumsum(counts)])
        before = np.concatenate([[0], np.cumsum(size[order])])
        fills = before[edges[1:]] - before[edges[:-1]]
        offset = before[:-1] - np.repeat(before[edges[:-1]], counts)
        for at in range(0, len(bins), 5000):
            z = min(at + 5000, len(bins))
            which = order[edges[at] : edges[z]]
            columns = [
                keys.take(pa.array(which)), pa.array(np.array(numbers, np.int32)[which]), pa.array(np.array(starts, np.int64)[which]), pa.array(size[which]),
                pa.array(np.array(sums, np.int64)[which]), pa.array(offset[edges[at] : edges[z]]),
            ]
            inner = pa.StructArray.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids_crc32", "offset"])
            members = pa.ListArray.from_arrays(pa.array((edges[at : z + 1] - edges[at]).astype(np.int32)), inner)
            n = z - at
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.zeros(n, np.int32)), pa.array(np.full(n, TaskContext.get().partitionId(), np.int64)), pa.array(np.arange(at, z)), pa.array(fills[at:z]), pa.array(capacity - fills[at:z] <= nearly_full), members],
                names=["level", "node", "bin", "fill", "closed", "members"],
            )

    level, depth = written(base.mapInArrow(local, schema), "bins"), 0
    done = []
    while True:
        done.append(level.where("closed"))
        rest = level.where("NOT closed")
        facts = rest.agg(F.count(F.lit(1)).alias("bins"), F.countDistinct("node").alias("nodes")).first()
        if not facts["bins"]:
            break
        # One node above ``fan_in`` nodes, more where these would give it too many bins.
        nodes = max(math.ceil(facts["nodes"] / fan_in), math.ceil(facts["bins"] / node_bins))
        settled = depth > 1 and facts["bins"] > 0.98 * left
        if settled:
            done.append(rest)
            break
        depth, left = depth + 1, facts["bins"]
        up = rest.withColumn("up", F.pmod(F.xxhash64("level", "node", "bin"), F.lit(nodes)))
        level = written(up.groupBy("up").applyInPandas(_merger(depth, nodes == 1, capacity, nearly_full), schema), "bins")
    out = done[0]
    for d in done[1:]:
        out = out.unionAll(d)
    # Level, node and number of a bin as one integer.
    number = F.shiftleft(F.col("level").cast("long"), 58) + F.shiftleft(F.col("node"), 34) + F.col("bin")
    return out.select(number.alias("sequence_id"), F.explode("members").alias("m")).select("m.doc_id", "m.piece", "m.start", "m.length", "m.ids_crc32", "sequence_id", "m.offset")


def _merger(depth: int, root: bool, capacity: int, nearly_full: int):  # noqa: ANN202
    """Best fit over the underfull bins of the nodes below one node; at the root every bin leaves."""

    def merge(key, pdf):  # noqa: ANN001, ANN202
        import pandas as pd

        pdf = pdf.sort_values(["level", "node", "bin"]).reset_index(drop=True)
        fill, members = pdf["fill"].tolist(), pdf["members"].tolist()
        bins = best_fit(fill, capacity)
        fills = [sum(fill[i] for i in b) for b in bins]
        rows = []
        for b in bins:
            off, row = 0, []
            for i in b:
                row += [{**m, "offset": m["offset"] + off} for m in members[i]]
                off += fill[i]
            rows.append(row)
        shut = [root or capacity - f <= nearly_full for f in fills]
        return pd.DataFrame({"level": depth, "node": int(key[0]), "bin": range(len(bins)), "fill": fills, "closed": shut, "members": rows})

    return merge
