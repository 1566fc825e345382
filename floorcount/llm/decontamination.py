"""Benchmark contamination by one pass of an Aho-Corasick automaton over each text.

Texts and benchmark items are brought to the same form: A-Z lower-cased, every run of other bytes below 0x80 that are
neither letters nor digits one blank. Windows of 13 item words (a shorter item is one window) are the automaton's
patterns, with a blank at both ends so that words match whole. A match's place gives the words it hits; their offsets in
the original text come from the same byte positions, as lower-casing keeps lengths.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorcount.llm.scratch import must_be_free, tidy

WINDOW = 13
#: Bytes of patterns in one automaton. A benchmark that needs more is dealt to several, which read the texts in turn.
BLOCK_BYTES = 8_000_000
FORM = bytes(b if b >= 0x80 or chr(b).isalnum() else 0x20 for b in (ord(chr(b).lower()) if b < 0x80 else b for b in range(256)))
WORD = re.compile(rb"[^ ]+")

FOUND = T.StructType([T.StructField("n_words", T.LongType()), T.StructField("words", T.ArrayType(T.StructType([T.StructField("first", T.IntegerType()), T.StructField("last", T.IntegerType())]))), T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))), T.StructField("items", T.ArrayType(T.StringType()))])


def words_of(text: bytes | None) -> list[bytes]:
    return (text or b"").translate(FORM).split()


def windows(words: list[bytes]) -> Iterator[bytes]:
    for i in range(max(1, len(words) - WINDOW + 1) if words else 0):
        yield b" ".join(words[i : i + WINDOW])


def blocks(benchmark: DataFrame, item: str = "item_id", text: str = "text") -> Iterator[list[tuple[bytes, str]]]:
    """(window, item) pairs, in lists of bounded size; items come one partition at a time, not all at once.

    Items with a null id or text, or no word, have none.
    """
    block, size = [], 0
    rows = benchmark.select(F.col(f"`{item}`").cast("string").alias("item"), F.col(f"`{text}`").cast("binary").alias("text")).dropna()
    for row in rows.toLocalIterator():
        for window in windows(words_of(bytes(row["text"]))):
            block.append((window, row["item"]))
            size += len(window) + len(row["item"])
            if size >= BLOCK_BYTES:
                yield block
                block, size = [], 0
    if block:
        yield block


class Automaton:
    def __init__(self, pairs: list[tuple[bytes, str]]):
        self.items: list[set[str]] = []
        self.trie = ahocorasick.Automaton()
        known: dict[str, int] = {}
        for window, item in pairs:
            pattern = f" {window.decode('latin-1')} "
            if pattern not in known:
                known[pattern] = len(self.items)
                self.items.append(set())
                self.trie.add_word(pattern, (len(self.items) - 1, len(pattern), window.count(b" ") + 1))
            self.items[known[pattern]].add(item)
        if known:
            self.trie.make_automaton()

    def find(self, text: bytes | None) -> tuple[int, list[tuple[int, int]], list[tuple[int, int]], list[str]]:
        """Number of words; first and last word, and character span in the text, of each hit stretch; items."""
        words = words_of(text)
        if not words or not self.items:
            return len(words), [], [], []
        line = f" {b' '.join(words).decode('latin-1')} "
        hits, items = [], set()
        for end, (k, width, n) in self.trie.iter(line):
            hits.append((end - width + 1, n))
            items |= self.items[k]
        if not hits:
            return len(words), [], [], []
        blank = np.flatnonzero(np.frombuffer(line.encode("latin-1"), dtype=np.uint8) == 0x20)
        stretches: list[list[int]] = []
        for first, n in sorted((int(np.searchsorted(blank, at)), n) for at, n in hits):
            if stretches and first <= stretches[-1][1] + 1:
                stretches[-1][1] = max(stretches[-1][1], first + n - 1)
            else:
                stretches.append([first, first + n - 1])
        places = [m.span() for m in WORD.finditer(text.translate(FORM))]
        spans = [(places[a][0], places[b][1]) for a, b in stretches]
        chars = [(len(text[:a].decode("utf-8", "replace")), len(text[:b].decode("utf-8", "replace"))) for a, b in spans]
        return len(words), [(a, b) for a, b in stretches], chars, sorted(items)


_built: dict[str, Automaton] = {}


def named(pairs: list[tuple[bytes, str]]) -> tuple[str, list[tuple[bytes, str]]]:
    """What is broadcast: the pairs under a name of their own, as a dropped list's address may be another's later."""
    return uuid.uuid4().hex, pairs


def built(sent: Broadcast) -> Automaton:
    key, pairs = sent.value
    if key not in _built:
        if len(_built) > 4:
            _built.clear()
        _built[key] = Automaton(pairs)
    return _built[key]


def merge(stretches: list[tuple[int, int]], near: int) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(stretches):
        if out and a <= out[-1][1] + near:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _scan(df: DataFrame, text: str, to: str, pairs: Broadcast, first: bool) -> DataFrame:
    fields = [f for f in df.schema.fields if f.name != to]
    schema = T.StructType([*fields, T.StructField(to, FOUND)])
    at = [f.name for f in fields].index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = built(pairs)
        for batch in batches:
            found = []
            before = [None] * batch.num_rows if first else batch.column(batch.num_columns - 1).to_pylist()
            for text_, old in zip(batch.column(at).cast(pa.binary()).to_pylist(), before):
                n, words, spans, items = automaton.find(text_)
                if old:
                    words = merge(words + [(x["first"], x["last"]) for x in old["words"]], 1)
                    spans = merge(spans + [(x["start"], x["end"]) for x in old["spans"]], 0)
                    items = sorted({*items, *old["items"]})
                found.append({"n_words": n, "words": [{"first": a, "last": b} for a, b in words], "spans": [{"start": a, "end": b} for a, b in spans], "items": items})
            kept = batch.columns[: len(fields)]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(found, _arrow())], names=schema.names)

    return df.mapInArrow(tidy(run), schema)


def _arrow() -> pa.DataType:
    pair = lambda a, b: pa.list_(pa.struct([(a, pa.int32()), (b, pa.int32())]))
    return pa.struct([("n_words", pa.int64()), ("words", pair("first", "last")), ("spans", pair("start", "end")), ("items", pa.list_(pa.string()))])


def scan(df: DataFrame, benchmark: DataFrame, text: str = "text", to: str = "found") -> DataFrame:
    """df with a struct `to`: n_words, hit stretches of words (0-based, inclusive), character spans in the original, items.

    Null and empty texts have no words and no hits; repeated rows are judged alike; an empty benchmark finds nothing. A
    column named `to` must not be there. Several blocks of a large benchmark follow each other over the same rows, with no
    shuffle.
    """
    must_be_free(df, to)
    context = df.sparkSession.sparkContext
    first = True
    for block in blocks(benchmark):
        df = _scan(df, text, to, context.broadcast(named(block)), first)
        first = False
    return _scan(df, text, to, context.broadcast(named([])), True) if first else df


def n_hit(found: str = "found"):
    return F.aggregate(f"{found}.words", F.lit(0).cast("long"), lambda s, x: s + x["last"] - x["first"] + 1)


def contaminated(found: str = "found"):
    """A twentieth of the words or more are hit."""
    return (n_hit(found) > 0) & (n_hit(found) * 20 >= F.col(f"{found}.n_words"))
