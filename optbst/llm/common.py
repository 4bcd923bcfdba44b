"""What the text operators share: word rules, column choice and Arrow helpers."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: ASCII white space, as a Java or RE2 character class.
SPACE_CLASS = r"[\x20\x09-\x0D]"
#: A word of letters, digits and every character beyond ASCII.
WORD_CLASS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Bytes outside such words become blanks, A-Z become a-z.
WORD_BYTES = bytes(
    (b + 32 if 65 <= b <= 90 else b) if b >= 128 or chr(b).isalnum() else 32 for b in range(256)
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def two_columns(df: DataFrame, key: str, text: str, as_key: str = "doc_id", as_text: str = "text") -> DataFrame:
    """Only the key and the text, under fixed names; a null text is empty. Other columns never clash."""
    return df.select(F.col(key).alias(as_key), F.coalesce(F.col(text), F.lit("")).alias(as_text))


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def fold_of(key: Column, modulus: int) -> Column:
    """crc32 of the key written as text, modulo ``modulus``; a null key counts as empty text."""
    return F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")) % modulus


def utf8(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def blank_words(text: str | None) -> list[bytes]:
    """Lower-cased words between ASCII white space."""
    return utf8(text).lower().split()


def alnum_bytes(text: str | None) -> bytes:
    """The text lower-cased with blanks for all that is in no word of letters, digits and characters beyond ASCII."""
    return utf8(text).translate(WORD_BYTES)


def alnum_words(text: str | None) -> list[bytes]:
    """Lower-cased words of letters, digits and characters beyond ASCII."""
    return alnum_bytes(text).split()


def map_batches(df: DataFrame, schema: str, make: Callable[[pa.RecordBatch], dict[str, object] | None]) -> DataFrame:
    """Apply ``make`` to every Arrow batch; it returns columns by name (numpy, lists or Arrow arrays)."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in sliced(batch):
                made = make(part)
                if made is not None:
                    yield pa.RecordBatch.from_arrays(
                        [made[f.name] if isinstance(made[f.name], pa.Array) else pa.array(made[f.name], f.type) for f in arrow], schema=arrow
                    )

    return df.mapInArrow(run, schema)


def sliced(batch: pa.RecordBatch, most_bytes: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that a part holds about ``most_bytes``; one row is never cut."""
    rows = batch.num_rows
    step = max(1, int(rows * most_bytes / max(1, batch.nbytes)))
    for at in range(0, rows, step):
        yield batch.slice(at, step)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (the public splitmix64 constants)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BYTE_VALUES = mix64(np.arange(1, 257, dtype=np.uint64))
_IS_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])


def word_keys(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(keys, words of each text) of the words between ASCII blanks, in order; contexts have keys of 0 and more.

    A word's key is a multilinear hash: random values of its bytes times random odd values of their
    places, summed, mixed with the length, without the last bit, and negative.
    """
    data = np.frombuffer(b" ".join([*texts, b""]), np.uint8)
    word = ~_IS_SPACE[data]
    before = np.empty_like(word)
    before[:1], before[1:] = False, word[:-1]
    starts = np.flatnonzero(word & ~before)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(len(texts), np.int64)
    lengths = np.flatnonzero(before & ~word) - starts
    first = np.cumsum(lengths) - lengths
    place = np.arange(int(lengths.sum())) - np.repeat(first, lengths)
    odd = mix64(np.arange(1, int(lengths.max()) + 1, dtype=np.uint64) << np.uint64(20)) | np.uint64(1)
    sums = np.add.reduceat(_BYTE_VALUES[data[word]] * odd[place], first)
    keys = -1 - (mix64(sums + lengths.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(1)).astype(np.int64)
    ends = np.cumsum([len(t) + 1 for t in texts])
    return keys, np.diff(np.searchsorted(starts, ends), prepend=0)
