"""Byte-level BPE encoding and decoding by backtracking over longest matches.

The vocabulary's byte strings are read as Latin-1 text, one character a byte, so that the trie of an Aho-Corasick automaton
over text tells how far a token can reach from a byte. A piece is then encoded from the left: take the longest token that may follow the
one before it, step to a shorter one where two neighbours would have merged differently, and go back a token where
nothing fits. A position that failed once is never tried again, so the work is linear in the piece. Two tokens may be
neighbours if merging their joined bytes by rank gives these two again. That is told without merging: their last merges are
undone, latest first, and no two parts that then meet at the border may merge before the step that was undone. Answers
are memoised.

Texts are cut into pieces by the pattern. A single blank between two characters that aren't blanks always starts a new
piece, so texts are split there first and each part's ids are kept in a bounded memo.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from functools import cached_property
from itertools import islice
from struct import pack

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorcount.llm.scratch import free_name, must_be_free, tidy

#: Entries of each memo; as many older ones are kept besides.
MEMO_ENTRIES = 150_000
#: What a memo keeps from one task to the next: its oldest entries of late, which the frequent words are among.
KEPT_ENTRIES = 30_000
#: Longer parts aren't kept: they hardly come again.
MEMO_CHARS = 64


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes and their ranks, of a file with a base64 token and a rank on each line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


class Memo(dict):
    """A bounded dict of two generations: what is asked for again moves to the young one, the old one goes when that is full."""

    def __init__(self):
        self.old: dict = {}

    def find(self, key):
        value = self.get(key)
        if value is None and (value := self.old.get(key)) is not None:
            self.put(key, value)
        return value

    def put(self, key, value) -> None:
        if len(self) >= MEMO_ENTRIES:
            self.old = dict(self)
            self.clear()
        self[key] = value

    def trim(self) -> None:
        self.old = {}
        kept = dict(islice(self.items(), KEPT_ENTRIES))
        self.clear()
        self.update(kept)


class ByteBpe:
    """Encodes and decodes with the merges that the ranks imply."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.tokens: list[bytes] = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.pieces = regex.compile(pattern).findall
        # words and a mark after them are pieces by themselves, if the pattern says so
        self.plain = self.pieces(" ab, cd.") == [" ab", ",", " cd", "."]
        self.blank = regex.compile(r"\s").match
        self.compatible, self.memo, self.piece_memo, self.part_memo = Memo(), Memo(), Memo(), Memo()
        self.split: dict[int, tuple[int, int] | None] = {}  # at most an entry for each token, as in the next
        self.prefix: dict[int, int] = {}

    @cached_property
    def widest(self) -> int:
        return max(map(len, self.ranks), default=1)

    @cached_property
    def latin(self) -> dict[str, int]:
        return {token.decode("latin-1"): rank for token, rank in self.ranks.items()}

    @cached_property
    def automaton(self) -> ahocorasick.Automaton:
        made = ahocorasick.Automaton()
        for token, rank in self.latin.items():
            made.add_word(token, rank)
        made.make_automaton()
        return made

    def merged(self, piece: bytes) -> list[int]:
        """Plain merging, lowest rank first: the definition; used for pairs of tokens only."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            ranked = [self.ranks.get(a + b, 1 << 60) for a, b in zip(parts, parts[1:])]
            if (best := min(ranked)) == 1 << 60:
                break
            at = ranked.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.ranks[p] for p in parts]

    def halves(self, rank: int) -> tuple[int, int] | None:
        """The tokens that a token's last merge joins; none of a byte. ValueError if it isn't made by merges of rising rank."""
        if rank not in self.split:
            token = self.tokens[rank]
            parts = [token[i : i + 1] for i in range(len(token))]
            while len(parts) > 2:
                ranked = [self.ranks.get(a + b, 1 << 60) for a, b in zip(parts, parts[1:])]
                if (best := min(ranked)) >= rank:
                    raise ValueError("no such merges")
                at = ranked.index(best)
                parts[at : at + 2] = [parts[at] + parts[at + 1]]
            made = tuple(self.ranks.get(p, 1 << 60) for p in parts) if len(parts) == 2 else None
            if made and any(len(p) > 1 and r >= rank for p, r in zip(parts, made)):
                raise ValueError("no such merges")
            self.split[rank] = made
        return self.split[rank]

    def stay_apart(self, left: int, right: int) -> bool:
        """Whether merging the joined bytes of two tokens gives these two: their merges run in the order of ranks, equal ones from the left."""
        ranks, tokens, before = self.ranks, self.tokens, 1 << 60
        while True:
            if ranks.get(tokens[left] + tokens[right], 1 << 60) < before:
                return False
            a, b = self.halves(left), self.halves(right)
            if a and (not b or left > right):
                left, before = a[1], left
            elif b:
                right, before = b[0], right + 1  # at equal ranks the border, further left, comes first
            else:
                return True

    def may_follow(self, left: int, right: int) -> bool:
        known = self.compatible.find(left << 32 | right)
        if known is None:
            try:
                known = self.stay_apart(left, right)
            except ValueError:
                known = self.merged(self.tokens[left] + self.tokens[right]) == [left, right]
            self.compatible.put(left << 32 | right, known)
        return known

    def shorter(self, rank: int) -> int:
        """The longest token that a token starts with, other than itself; -1: none."""
        found = self.prefix.get(rank)
        if found is None:
            token, found = self.tokens[rank], -1
            for width in range(len(token) - 1, 0, -1):
                if (found := self.ranks.get(token[:width], -1)) >= 0:
                    break
            self.prefix[rank] = found
        return found

    def encode_piece(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        text, ids, reach, most, tokens = piece.decode("latin-1"), self.latin, self.automaton.longest_prefix, self.widest, self.tokens
        known, may_follow, prefix, shorter = self.compatible.get, self.may_follow, self.prefix.get, self.shorter
        usable = bytearray(b"\x01") * (len(piece) + 1)
        out: list[int] = []
        at, last, rank = 0, -1, None
        while at < len(piece):
            if rank is None:
                width = reach(text[at : at + most])
                while width and (rank := ids.get(text[at : at + width])) is None:
                    width -= 1
                if not width:
                    rank = -1
            while rank >= 0:
                end = at + len(tokens[rank])
                if usable[end]:
                    if last < 0:
                        break
                    if (fits := known(last << 32 | rank)) is None:
                        fits = may_follow(last, rank)
                    if fits:
                        break
                if (less := prefix(rank)) is None:
                    less = shorter(rank)
                rank = less
            if rank >= 0:
                out.append(rank)
                at, last, rank = end, rank, None
            else:
                usable[at] = 0
                if not out:
                    raise ValueError("the vocabulary lacks a byte of the text")
                gone = out.pop()
                at -= len(tokens[gone])
                last, rank = out[-1] if out else -1, shorter(gone)
        return out

    def _ids(self, piece: str) -> bytes:
        ids = self.encode_piece(piece.encode("utf-8"))
        return pack(f"<{len(ids)}I", *ids)

    def _piece(self, piece: str) -> bytes:
        """Ids of a piece of the pattern; those of a blank and a word are kept as that word's."""
        if self.plain and piece[0] == " " and piece[1:].isalpha():
            return self._word(piece[1:])
        known = self.piece_memo.find(piece)
        if known is None:
            known = self._ids(piece)
            if len(piece) <= MEMO_CHARS:
                self.piece_memo.put(piece, known)
        return known

    def _word(self, word: str) -> bytes:
        known = self.memo.find(word)
        if known is None:
            known = self._ids(" " + word)
            if len(word) <= MEMO_CHARS:
                self.memo.put(word, known)
        return known

    def _packed(self, text: str) -> bytes:
        return b"".join(map(self._piece, self.pieces(text)))

    def _part(self, part: str) -> bytes | None:
        """Ids of a blank and part; None where part can't be cut off from what stands around it."""
        if not part:
            return None
        if self.plain:
            if part.isalpha():
                return self._word(part)
            if part[-1] in ".," and part[:-1].isalpha():
                return self._word(part[:-1]) + self._piece(part[-1])
        if self.blank(part[0]) or self.blank(part[-1]):
            return None
        known = self.part_memo.find(part)
        if known is None:
            known = self._packed(" " + part)
            if len(part) <= MEMO_CHARS:
                self.part_memo.put(part, known)
        return known

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers; of null, none."""
        if not text:
            return b""
        parts = text.split(" ")
        known = list(map(self.memo.get, parts))
        out: list[bytes] = []
        open_from, closed = 0, False  # the parts since open_from are encoded together; closed: the last one may be cut off
        for i, part in enumerate(parts):
            ids = known[i]
            if ids is None:
                ids = self._part(part)
            if ids is None:
                closed = False
                continue
            if closed:
                out.append(ids)
                open_from = i + 1
            elif i == 0 or not self._may_cut(parts[i - 1]):
                closed = True  # it ends well, but what stands before it is open
                out.append(self._packed((" " if open_from else "") + " ".join(parts[open_from : i + 1])))
                open_from = i + 1
                continue
            else:
                out.append(self._packed((" " if open_from else "") + " ".join(parts[open_from:i])))
                out.append(ids)
                open_from = i + 1
            closed = True
        if open_from < len(parts):
            out.append(self._packed((" " if open_from else "") + " ".join(parts[open_from:])))
        return b"".join(out)

    def _may_cut(self, before: str) -> bool:
        return bool(before) and not self.blank(before[-1])

    def rest(self) -> None:
        """Shrinks the memos at the end of a task."""
        for memo in (self.compatible, self.memo, self.piece_memo, self.part_memo):
            memo.trim()

    def decode(self, ids: bytes | None) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(ids or b"", dtype="<u4").tolist()))

    @cached_property
    def token_array(self) -> pa.Array:
        return pa.array(self.tokens, pa.large_binary())

    def encode_all(self, texts: pa.Array) -> pa.Array:
        try:
            values = texts.to_pylist()
        except UnicodeDecodeError:
            values = [None if x is None else x.decode("utf-8", "replace") for x in texts.cast(pa.binary()).to_pylist()]
        return pa.array(map(self.encode, values), pa.binary())

    def decode_all(self, ids: pa.Array) -> pa.Array:
        """decode() of each: the tokens of all are laid one after the other at once, then cut where each row ends."""
        ids = ids.cast(pa.large_binary()).fill_null(b"")
        _, ends, data = ids.buffers()
        ends = np.frombuffer(ends, dtype=np.int64)[ids.offset : ids.offset + len(ids) + 1] if len(ids) else np.zeros(1, dtype=np.int64)
        if ends[-1] == ends[0]:
            return pa.array([b""] * len(ids), pa.binary())
        whole = self.token_array.take(pa.array(np.frombuffer(data, dtype="<u4", count=(ends[-1] - ends[0]) // 4, offset=ends[0]).astype(np.int64)))
        cuts = np.frombuffer(whole.buffers()[1], dtype=np.int64)[whole.offset :][(ends - ends[0]) // 4]
        return pa.Array.from_buffers(pa.large_binary(), len(ids), [None, pa.py_buffer(np.ascontiguousarray(cuts)), whole.buffers()[2]]).cast(pa.binary())


_open: dict[tuple[str, str], ByteBpe] = {}


def opened(vocabulary: str, pattern: str) -> ByteBpe:
    """One coder a worker process and vocabulary."""
    if (vocabulary, pattern) not in _open:
        _open.clear()
        _open[vocabulary, pattern] = ByteBpe(read_ranks(vocabulary), pattern)
    return _open[vocabulary, pattern]


def _with_columns(df: DataFrame, names: list[str], of: str, work, *hows: str) -> DataFrame:
    """df with binary columns of these names: the first made of `of`, each other one of the column before it."""
    schema = T.StructType([*df.schema.fields, *[T.StructField(name, T.BinaryType(), True) for name in names]])
    given = free_name(df, "_given")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = work()
        steps = [getattr(coder, how) for how in hows]
        for batch in batches:
            for start in range(0, batch.num_rows, 256):  # bounds what stands in memory besides the batch
                part = batch.slice(start, 256)
                made = [part.column(given)]
                for step in steps:
                    made.append(step(made[-1]))
                keep = [part.column(c) for c in range(part.num_columns - 1)]
                yield pa.RecordBatch.from_arrays([*keep, *made[1:]], names=schema.names)
        coder.rest()

    return df.withColumn(given, F.col(of)).mapInArrow(tidy(run), schema)


def encode(df: DataFrame, vocabulary: str, pattern: str, text: str = "text", to: str = "token_ids") -> DataFrame:
    """df with a binary column of ids, little-endian unsigned 32-bit, for each whole text.

    vocabulary: path of the rank file, there on each executor. Null and empty texts have no ids. Bytes that are not UTF-8 are
    encoded as U+FFFD. Repeated rows are encoded
    alike, other columns pass through; an existing column called `to` raises an error. See id_array() for an array.
    """
    must_be_free(df, to)
    return _with_columns(df, [to], text, lambda: opened(vocabulary, pattern), "encode_all")


def decode(df: DataFrame, vocabulary: str, pattern: str, ids: str = "token_ids", to: str = "decoded") -> DataFrame:
    """df with the bytes that the ids stand for; null ids give no bytes."""
    must_be_free(df, to)
    return _with_columns(df, [to], ids, lambda: opened(vocabulary, pattern), "decode_all")


def round_trip(df: DataFrame, vocabulary: str, pattern: str, text: str = "text", to: str = "token_ids", back: str = "decoded") -> DataFrame:
    """encode(), then decode() of its ids, in one pass: a task has one worker with a coder, where the two calls have two."""
    must_be_free(df, to, back)
    return _with_columns(df, [to, back], text, lambda: opened(vocabulary, pattern), "encode_all", "decode_all")


def id_array(ids: Column) -> Column:
    """array<bigint> of packed ids, made in the JVM."""
    byte = lambda i, k: F.conv(F.hex(F.substring(ids, i * 4 + 1 + k, F.lit(1))), 16, 10).cast("bigint")
    n = (F.octet_length(ids) / 4).cast("int")
    one = lambda i: byte(i, 0) + byte(i, 1) * 256 + byte(i, 2) * 65536 + byte(i, 3) * 16777216
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), one)).otherwise(F.array().cast("array<bigint>"))
