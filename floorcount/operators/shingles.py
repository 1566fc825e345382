"""Level bitmaps of a text's shingles, made where the text is.

A text has about as many shingles as characters. As rows they would be copied and hashed one string at a time; here each
task hashes a text's shingles in one sweep and lets only bitmaps out: at most m rows for a group and task, whatever was read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorcount.functions import hashing as H
from floorcount.operators.state import levels_of

#: Groups that a task holds tables of, 64 bytes a register each, before it lets their bitmaps out.
HELD = 64
#: Odd 64-bit multiplier of the rolling polynomial: a fixed value.
STEP = 0x9E3779B97F4A7C15


def rolled(values: np.ndarray, span: int) -> np.ndarray:
    """A 64-bit hash of each run of `span` values: polynomials read off one running sum, then mixed."""
    n = len(values) - span + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    up = np.full(len(values), STEP, dtype=np.uint64)
    up[0] = 1
    np.multiply.accumulate(up, out=up)
    total = np.zeros(len(values) + 1, dtype=np.uint64)
    np.cumsum(mixed(values.astype(np.uint64) + np.uint64(1)) * up, out=total[1:])
    # each difference holds the run's polynomial times a power, which the inverse power takes away
    down = np.full(n, pow(STEP, -1, 1 << 64), dtype=np.uint64)
    down[0] = 1
    np.multiply.accumulate(down, out=down)
    return mixed((total[span:] - total[:n]) * down)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def char_hashes(text: str, span: int, kind: str) -> np.ndarray:
    """Hashes of all runs of `span` characters. md5_60 equals what SQL makes of the run as a string."""
    if len(text) < span:
        return np.empty(0, dtype=np.uint64)
    if kind != "md5_60":
        return rolled(np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4"), span)
    raw, md5 = text.encode(), hashlib.md5
    if len(raw) == len(text):
        cut = (raw[i : i + span] for i in range(len(raw) - span + 1))
    else:
        at = np.flatnonzero((np.frombuffer(raw, dtype=np.uint8) & 0xC0) != 0x80).tolist() + [len(raw)]
        cut = (raw[a:b] for a, b in zip(at, at[span:]))
    heads = b"".join([md5(x).digest()[:8] for x in cut])
    return np.frombuffer(heads, dtype=">u8").astype(np.uint64) >> np.uint64(4)


def word_hashes(text: str, span: int, kind: str) -> np.ndarray:
    """Hashes of all runs of `span` words, parted by single blanks."""
    words = text.split(" ")
    if len(words) < span:
        return np.empty(0, dtype=np.uint64)
    if kind == "md5_60":
        raw, md5 = [w.encode() for w in words], hashlib.md5
        heads = b"".join([md5(b" ".join(raw[i : i + span])).digest()[:8] for i in range(len(raw) - span + 1)])
        return np.frombuffer(heads, dtype=">u8").astype(np.uint64) >> np.uint64(4)
    one = {w: int.from_bytes(hashlib.blake2b(w.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little") for w in set(words)}
    return rolled(np.array([one[w] for w in words], dtype=np.uint64), span)


def _levels(df: DataFrame, text: str, by: Sequence[str], m: int, kind: str, hashes: Callable[[str], np.ndarray]) -> DataFrame:
    if m & (m - 1):
        raise ValueError("mask addressing needs a power of two")
    width = H.WIDTH[kind]
    given = df.select(*[F.col(c) for c in by], F.col(text).cast("string").alias("_text"))
    schema = T.StructType([*given.schema.fields[: len(by)], T.StructField("reg", T.IntegerType()), T.StructField("bits", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for key, seen in held.items():
                bits = np.packbits(seen.reshape(m, 64), axis=1, bitorder="little").view("<i8").ravel()
                reg = np.flatnonzero(bits)
                yield pa.RecordBatch.from_arrays([*[pa.array([k] * len(reg), t) for k, t in zip(key, kinds)], pa.array(reg, pa.int32()), pa.array(bits[reg], pa.int64())], names=schema.names)

        kinds: list[pa.DataType] = []
        for batch in batches:
            kinds = [batch.column(i).type for i in range(len(by))]
            keys = list(zip(*[batch.column(i).to_pylist() for i in range(len(by))])) if by else [()] * batch.num_rows
            texts = batch.column(batch.num_columns - 1).cast(pa.binary())
            for key, raw in zip(keys, texts):
                if not raw.is_valid:
                    continue
                h = hashes(raw.as_py().decode("utf-8", "replace"))
                if not len(h):
                    continue
                if key not in held:
                    if len(held) >= HELD:
                        yield from out()
                        held.clear()
                    held[key] = np.zeros(m * 64, dtype=bool)
                held[key][(h & np.uint64(m - 1)).astype(np.int64) * 64 + levels_of(h, width)] = True
        yield from out()

    bitmaps = given.mapInArrow(run, schema)
    return bitmaps.groupBy(*by, "reg").agg(F.bit_or("bits").alias("bits"))


def shingle_levels(df: DataFrame, text: str = "text", by: Sequence[str] = (), m: int = 2048, span: int = 31, kind: str = "xxhash64") -> DataFrame:
    """Rows (by..., reg, bits) of all runs of `span` characters; texts with fewer, and null ones, have none.

    kind: md5_60 hashes each run as a string, as SQL can; any other takes a rolling hash of 64 bits.
    """
    return _levels(df, text, by, m, kind, lambda t: char_hashes(t, span, kind))


def ngram_levels(df: DataFrame, text: str = "text", by: Sequence[str] = (), m: int = 2048, span: int = 3, kind: str = "xxhash64") -> DataFrame:
    """Rows (by..., reg, bits) of all runs of `span` words between single blanks."""
    return _levels(df, text, by, m, kind, lambda t: word_hashes(t, span, kind))
