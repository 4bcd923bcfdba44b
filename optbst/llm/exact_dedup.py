"""Exact duplicates by deterministic block naming (DataFrame functions only).

A normalised text (ASCII white space deleted) is cut into blocks of fixed size. Equal blocks get
one integer: the distinct blocks are sorted and numbered. Then neighbouring pairs of integers are
named in the same way, again and again, until one integer is left for each document. Texts with
as many blocks are equal exactly when this integer is: names are ranks of the things themselves,
not hashes, so there are no collisions.

Scale: one shuffle carries block texts, behind a map-side aggregation, so a block shared by a
third of all rows is one row for each map task. Distinct blocks are sorted inside their hash
partition and numbered there, so no task sees them all. Names go back to documents by a 64-bit key
of the block, a few bytes instead of the block. Keys that more than one block has are found by
counting, and those blocks get names in a round of their own that joins on their full texts; so
the key decides nothing. Levels halve the rows, and only documents of several blocks reach the
second one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import written
from .common import SPACE_CLASS, two_columns

#: Bytes of UTF-8 in a block, which may end inside a character.
BLOCK_CHARS = 2048


def normalised(text: Column) -> Column:
    """Text without ASCII white space; null is empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_CLASS + "+", "")


def _numbered(distinct: DataFrame, *order: str) -> DataFrame:
    """Sort the rows of each hash partition and number them: (partition, rank) as one integer."""
    return distinct.sortWithinPartitions(*order).withColumn("name", F.monotonically_increasing_id())


def block_identity(rows: DataFrame, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """``rows(row, norm)`` to one ``(row, n_blocks, identity)`` for each ``row``.

    Equal (n_blocks, identity) means equal ``norm`` and the reverse. An empty norm is one empty
    block. Rows that repeat ``row`` must repeat ``norm`` and are one.
    """
    # Numbers of blocks are exploded, not blocks: a piece of bytes is cut at its place, without an array of copies or a search from the start.
    whole = rows.select("row", F.col("norm").cast("binary").alias("bytes")).withColumn("n_blocks", F.expr(f"cast(greatest(octet_length(bytes) - 1, 0) / {block_chars} AS int) + 1"))
    blocks = whole.select("row", "n_blocks", "bytes", F.explode(F.expr("sequence(0, n_blocks - 1)")).alias("at"))
    blocks = blocks.select("row", "n_blocks", "at", F.expr(f"substring(bytes, at * {block_chars} + 1, {block_chars})").alias("block"))
    blocks = blocks.withColumn("short", F.xxhash64("block"))
    names = written(_numbered(blocks.select("short", "block").distinct(), "short", "block").select("short", "name"), "block-names")
    keys = written(names.groupBy("short").agg(F.count(F.lit(1)).alias("n"), F.min("name").alias("name")), "block-keys")
    named = blocks.select("row", "n_blocks", "at", "short").join(keys.where("n = 1").select("short", "name"), "short").select("row", "n_blocks", "at", "name")
    clash = keys.where("n > 1").select("short")
    if clash.take(1):
        shared = blocks.join(clash, "short", "left_semi")
        own = written(_numbered(shared.select("block").distinct(), "block"), "clash-names")
        named = named.unionByName(shared.join(own, "block").select("row", "n_blocks", "at", (-1 - F.col("name")).alias("name")))
    level = written(named.groupBy("row", "n_blocks", "at").agg(F.min("name").alias("name")), "block-level")
    done = [level.where("n_blocks = 1").select("row", "n_blocks", F.col("name").alias("identity"))]
    level = level.where("n_blocks > 1").withColumn("left", F.col("n_blocks"))
    longest = level.agg(F.max("left")).first()[0] or 1
    while longest > 1:
        # An odd block at the end has no right neighbour and pairs with nothing, which is also a name.
        pairs = level.groupBy("row", "n_blocks", "left", F.floor(F.col("at") / 2).cast("int").alias("half")).agg(
            F.max(F.when(F.col("at") % 2 == 0, F.col("name"))).alias("a"), F.coalesce(F.max(F.when(F.col("at") % 2 == 1, F.col("name"))), F.lit(-1)).alias("b")
        )
        pairs = written(pairs, "pairs")
        pair_names = written(_numbered(pairs.select("a", "b").distinct(), "a", "b"), "pair-names")
        level = written(
            pairs.join(pair_names, ["a", "b"]).select("row", "n_blocks", F.col("half").alias("at"), "name", F.ceil(F.col("left") / 2).cast("int").alias("left")), "level"
        )
        done.append(level.where("left = 1").select("row", "n_blocks", F.col("name").alias("identity")))
        level = level.where("left > 1")
        longest = -(-longest // 2)
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def exact_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Of texts that are equal without ASCII white space, the row with the most code points stays,
    then the smallest key. Null and blank texts are one group. A null key loses every tie; rows that
    repeat both key and length of the one that stays are all marked kept. An empty table gives no rows.
    """
    base = two_columns(docs, key, text).withColumn("norm", normalised(F.col("text")))
    # Ties blocks to their row; rows with one key and one text are alike and share it.
    base = base.withColumn("row", F.struct(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("k"), F.xxhash64("doc_id", "text").alias("h")))
    facts = base.select("row", "doc_id", F.char_length("text").alias("points"), F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("digest"))
    identity = written(block_identity(base.select("row", "norm"), block_chars), "identity")
    rows = written(facts.join(identity, "row"), "rows")
    best = rows.groupBy("n_blocks", "identity").agg(
        F.count(F.lit(1)).alias("group_size"), F.min(F.struct((-F.col("points")).alias("p"), F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("keep_id"))).alias("best")
    )
    best = written(best, "best")
    joined = rows.join(best, ["n_blocks", "identity"])
    return joined.select(
        "doc_id",
        F.col("best.keep_id").alias("keep_id"),
        "group_size",
        (F.col("doc_id").eqNullSafe(F.col("best.keep_id")) & (-F.col("points") == F.col("best.p"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
