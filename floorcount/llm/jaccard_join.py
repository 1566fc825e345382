"""Exact set-similarity join on word shingles, and the groups its links form.

A document's set holds the hashes of its distinct five-word shingles. Documents with equal sets form a class, which one
of them stands for. A set's tokens are ordered rare first: those in a bounded table of frequent tokens last, by their
count, the others by their hash. Two sets whose Jaccard similarity reaches the limit share a token among the first
n - ceil(limit * n) + 1 of each, so only these are dealt out by token; tokens of one document alone are dropped at once.

What is asked for is groups, so not every pair of a token's documents has to be looked at. First come meetings that grow
with the number of postings alone: each document meets the least id of the lists of its first tokens, then neighbours of
like size in each list, in another order each round. Pairs pass the length filter, the positional filter, the parity
filter, the suffix filter (sizes of matching hash ranges bound the overlap) and then the exact count, once a pair; the
links merge groups, and lists of one group are dropped. Last, in the lists that still hold several groups, every two
documents of different groups and like size meet, which leaves out no link between groups. A pair meets in many lists; it
is taken from the first token that both sets hold only, which the tokens before it in either set's order tell.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from floorcount.llm.components import components
from floorcount.llm.scratch import Bucketed, Scratch, tidy

SHINGLE = 5
#: Similarity limit in hundredths.
LIMIT = 75
#: Entries of the frequent-token table that every executor gets: 16 bytes each.
FREQUENT = 32_768
#: Tokens after which a task reports those that it saw often, and how many at most; sets that a task remembers to give them once.
CHUNK, CHUNK_FREQUENT, REMEMBERED = 1_000_000, 8_192, 50_000
#: At first, each document meets the least id of the lists of its first tokens, so many of them.
EARLY = 4
#: Rounds of neighbours, at most (another follows where most of the pairs were links), and how many neighbours each document meets in a list.
ROUNDS, NEIGHBOURS = 2, 2
#: Documents among which neighbours are drawn, over NEIGHBOURS; longer lists are dealt out by hash, anew each round.
DRAWN = 512
#: Documents of a list that one task holds against the others of the list; longer lists are dealt out.
BLOCK = 4_096
#: Sets that reach the limit are of the same or the next size class; the margin keeps rounding out of it.
CLASS = 1.05 * 100 / LIMIT
#: Words of 64 bits in the table that tells whose sets a round needs; it goes to all tasks, 16 bytes each.
WANTED = 131_072
#: Tokens before each posting that tell whether two sets have met already; a pair that they miss meets again and is told apart later.
BEFORE = 8

ODDS = ("o0", "o1", "o2", "o3")
LOWER = bytes(range(256)).lower()
ODD = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))  # mixing constants
BASE = 0xD6E8FEB86659FD93
WHITE = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
#: A random number for each byte, A-Z as a-z: the same on every executor.
VALUES = np.random.default_rng(20).integers(1, 1 << 63, 256, dtype=np.uint64)[np.frombuffer(LOWER, dtype=np.uint8)] * np.uint64(2) + np.uint64(1)
ROWS = 256


class _Powers:
    """Powers of BASE and of its inverse modulo 2^64, as far as the longest text needed them."""

    def __init__(self):
        self.up = self.down = np.empty(0, dtype=np.uint64)

    def grown(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(1 << 16, 1 << (n - 1).bit_length())
            made = []
            for base in (BASE, pow(BASE, -1, 1 << 64)):
                steps = np.full(size, np.uint64(base))
                steps[0] = np.uint64(1)
                made.append(np.multiply.accumulate(steps))
            self.up, self.down = made
        return self.up, self.down


_powers = _Powers()


def word_hashes(text: bytes) -> np.ndarray:
    """A hash of each word, A-Z lower-cased: polynomials over bytes, read off one running sum over the text."""
    raw = np.frombuffer(text, dtype=np.uint8)
    edge = np.flatnonzero(np.diff(WHITE[raw], prepend=True, append=True))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.empty(0, dtype=np.uint64)
    up, down = _powers.grown(len(raw) + 1)
    total = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum(VALUES[raw] * up[: len(raw)], out=total[1:])
    return _mix((total[end] - total[start]) * down[start])


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * ODD[1]
    x = (x ^ (x >> np.uint64(27))) * ODD[2]
    return x ^ (x >> np.uint64(31))


def shingle_set(text: bytes | None) -> np.ndarray:
    """Sorted hashes (uint64) of the distinct shingles; of a text with fewer words than a shingle, one of them all."""
    h = word_hashes(text or b"")
    if not len(h):
        return h
    width = min(SHINGLE, len(h))
    n = len(h) - width + 1
    out = np.full(n, width, dtype=np.uint64)
    for k in range(width):
        out = _mix(out * ODD[0] + h[k : k + n])
    out.sort()
    return out[np.concatenate([[True], out[1:] != out[:-1]])]


def _slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """A batch in parts of few rows, which bounds what stands in memory beside it."""
    for start in range(0, batch.num_rows, ROWS):
        yield batch.slice(start, ROWS)


def set_key(tokens: np.ndarray) -> tuple[int, int]:
    digest = xxhash.xxh128_digest(tokens.tobytes())
    return int.from_bytes(digest[:8], "big", signed=True), int.from_bytes(digest[8:], "big", signed=True)


def prefix_length(n: int) -> int:
    return n - (LIMIT * n + 99) // 100 + 1


def ranges(tokens: np.ndarray) -> bytes:
    """How many tokens fall into each of 2^k equal ranges of hashes, as bytes after k; about four a range."""
    k = max(4, min(16, int(len(tokens)).bit_length() - 2))
    counts = np.bincount((tokens >> np.uint64(64 - k)).astype(np.int64), minlength=1 << k)
    return bytes([k]) + counts.astype("<u2" if counts.max(initial=0) > 255 else "u1").tobytes()


def parities(tokens: np.ndarray) -> np.ndarray:
    """256 bits in four words: whether an odd number of tokens falls to each. What differs between two sets' bits is at most what differs between the sets."""
    odd = np.bincount((tokens & np.uint64(255)).astype(np.int64), minlength=256) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def _counts(packed: bytes) -> np.ndarray:
    k = packed[0]
    return np.frombuffer(packed, dtype="u1" if len(packed) == 1 + (1 << k) else "<u2", offset=1).astype(np.int64)


def overlap_bound(a: bytes, b: bytes) -> int:
    """No two sets with these range counts have more tokens in common."""
    x, y = _counts(a), _counts(b)
    size = min(len(x), len(y))
    return int(np.minimum(x.reshape(size, -1).sum(axis=1), y.reshape(size, -1).sum(axis=1)).sum())


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def _texts(docs: DataFrame, doc: str, text: str) -> DataFrame:
    return docs.select(F.col(f"`{doc}`").alias("id"), F.col(f"`{text}`").cast("string").cast("binary").alias("text"))


def profiles(texts: DataFrame) -> DataFrame:
    """A row for each document: id, n, c1, c2 (the set's key), sig, o0 to o3 (parities); and rows (token, docs) of what a task saw often."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, seen = [], 0, set()

        def often() -> pa.RecordBatch:
            tokens, count = np.unique(np.concatenate(held), return_counts=True)
            top = np.argsort(-count, kind="stable")[:CHUNK_FREQUENT]
            top = top[count[top] > 2]
            none = pa.nulls(len(top), pa.int64())
            return pa.RecordBatch.from_arrays([none, none, none, none, pa.nulls(len(top), pa.binary()), none, none, none, none, pa.array(_signed(tokens[top])), pa.array(count[top].astype(np.int64))], names=names)

        names = ["id", "n", "c1", "c2", "sig", *ODDS, "token", "docs"]
        for batch in (part for whole in batches for part in _slices(whole)):
            rows = []
            for text in batch.column("text").to_pylist():
                tokens = shingle_set(text)
                key = set_key(tokens)
                rows.append((len(tokens), *key, ranges(tokens), *parities(tokens).tolist()))
                if len(tokens) and key not in seen:
                    if len(seen) > REMEMBERED:
                        seen.clear()
                    seen.add(key)
                    held.append(tokens)
                    size += len(tokens)
            n, c1, c2, sig, *odd = zip(*rows)
            none = pa.nulls(len(rows), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("id").cast(pa.int64()), pa.array(n, pa.int64()), pa.array(c1, pa.int64()), pa.array(c2, pa.int64()), pa.array(sig, pa.binary()), *[pa.array(x, pa.int64()) for x in odd], none, none], names=names)
            if size >= CHUNK:
                yield often()
                held, size = [], 0
        if held:
            yield often()

    return texts.mapInArrow(tidy(run), "id long, n long, c1 long, c2 long, sig binary, o0 long, o1 long, o2 long, o3 long, token long, docs long")


def frequent_tokens(profile: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The FREQUENT most frequent tokens, sorted, and their counts: a table of fixed size, whatever the input."""
    top = profile.filter("token is not null").groupBy("token").agg(F.sum("docs").alias("docs")).orderBy(F.desc("docs"), "token").limit(FREQUENT)
    table = top.toArrow()
    tokens = table.column("token").to_numpy().astype(np.int64).view(np.uint64)
    order = np.argsort(tokens)
    return tokens[order], table.column("docs").to_numpy().astype(np.int64)[order]


def postings(texts: DataFrame, frequent: Broadcast) -> DataFrame:
    """Rows (token, id, n, pos, often) of each set's prefix. Equal sets that one task meets give theirs once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, counts = frequent.value
        seen: set[tuple[int, int]] = set()
        for batch in (part for whole in batches for part in _slices(whole)):
            out: list[tuple[np.ndarray, ...]] = []
            size = 0
            for doc, text in zip(batch.column("id").to_pylist(), batch.column("text").to_pylist()):
                tokens = shingle_set(text)
                if doc is None or not len(tokens) or (key := set_key(tokens)) in seen:
                    continue
                if len(seen) > REMEMBERED:
                    seen.clear()
                seen.add(key)
                weight = np.zeros(len(tokens), dtype=np.int64)
                if len(known):
                    at = np.minimum(np.searchsorted(known, tokens), len(known) - 1)
                    weight = np.where(known[at] == tokens, counts[at], 0)
                    if weight.any():
                        order = np.lexsort((tokens, weight))
                        tokens, weight = tokens[order], weight[order]
                p = prefix_length(len(tokens))
                out.append((tokens[:p], np.full(p, doc, dtype=np.int64), np.full(p, len(tokens), dtype=np.int32), np.arange(p, dtype=np.int32), weight[:p] > 0))
                size += p
                if size > 500_000:
                    yield _batch(out)
                    out, size = [], 0
            if out:
                yield _batch(out)

    return texts.mapInArrow(tidy(run), "token long, id long, n int, pos int, often boolean")


def _batch(out: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
    token, *rest = (np.concatenate(x) for x in zip(*out))
    return pa.RecordBatch.from_arrays([pa.array(_signed(token)), *map(pa.array, rest)], names=["token", "id", "n", "pos", "often"])


def shared(entries: DataFrame) -> DataFrame:
    """The postings whose token several ids have, one of them of like size. Frequent tokens are known to be shared, and are spread.

    A set whose first common token stands at pos reaches the limit with sets of up to `most` tokens only; of two such sets
    the smaller one's `most` is at least the larger one's size.
    """
    salt = F.when(F.col("often"), F.pmod(F.xxhash64("id"), F.lit(64))).otherwise(0)
    most = F.least(F.floor(F.col("n") * 100 / LIMIT), F.floor((F.col("n") - F.col("pos")) * (100 + LIMIT) / LIMIT) - F.col("n"))
    by = W.partitionBy("token", "salt").orderBy("n")
    whole, before = by.rowsBetween(W.unboundedPreceding, W.unboundedFollowing), by.rowsBetween(W.unboundedPreceding, -1)
    met = {"lo": F.min("id").over(whole), "hi": F.max("id").over(whole), "larger": F.lead("n").over(by), "reach": F.max("most").over(before)}
    both = entries.withColumn("salt", salt).repartition("token", "salt").withColumn("most", most).withColumns(met)
    return both.filter("often or (lo < hi and (larger <= most or n <= reach))").select("token", "id", "n", "pos")


def may_link(x: Callable[[str], Column], y: Callable[[str], Column]) -> Column:
    """Whether two postings of one token, the first that both sets hold, may be of sets that reach the limit: length, position, parities."""
    n, m = x("n"), y("n")
    near = F.least(n, m) * 100 >= F.greatest(n, m) * LIMIT
    # the first token that two sets share has none in common before it, so only it and what follows can be shared. A pair
    # that is turned down by a later token it shares comes again by its first one, in the list of that
    after = F.least(n - x("pos"), m - y("pos")) * (100 + LIMIT) >= (n + m).cast("long") * LIMIT
    # two sets of n and m tokens that reach the limit differ by at most (n + m) * (100 - limit) / (100 + limit) tokens
    differ = sum((F.bit_count(x(o).bitwiseXOR(y(o))) for o in ODDS), F.lit(0))
    return near & after & (differ * (100 + LIMIT) <= (n + m) * (100 - LIMIT))


def _ordered(a: Column, b: Column) -> list[Column]:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def _renamed(rows: DataFrame) -> DataFrame:
    return rows.select(*[F.col(c).alias(f"p_{c}") for c in rows.columns])


def _x(name: str) -> Column:
    return F.col(name)


def _y(name: str) -> Column:
    return F.col(f"p_{name}")


def least_pairs(lists: DataFrame) -> DataFrame:
    """Distinct pairs (a, b), a < b, of a document and the least id of the lists of its first tokens."""
    least = lists.groupBy(F.col("token").alias("t")).agg(F.min("id").alias("least"))
    pivots = _renamed(lists.join(least, (F.col("token") == F.col("t")) & (F.col("id") == F.col("least"))).select(*lists.columns))
    first = lists.withColumn("rank", F.row_number().over(W.partitionBy("id").orderBy("pos", "token"))).filter(F.col("rank") <= EARLY)
    return first.join(pivots, (F.col("token") == F.col("p_token")) & (F.col("id") > F.col("p_id")) & may_link(_x, _y)).select(*_ordered(F.col("id"), F.col("p_id"))).distinct()


def _size_class(shift: float = 0.0) -> Column:
    return F.floor(F.log(F.col("n").cast("double")) / float(np.log(CLASS)) + shift).cast("int")


def neighbour_pairs(lists: DataFrame, number: int) -> DataFrame:
    """Distinct pairs of documents of different groups that follow each other in a list, dealt by size, in an order by hash."""
    dealt = lists.withColumns({"class": _size_class(number / 2), "part": F.pmod(F.xxhash64("id", F.lit(number)), F.ceil(F.col("k") * NEIGHBOURS / DRAWN))})
    order = W.partitionBy("token", "class", "part").orderBy(F.xxhash64("id", "token", F.lit(number)), "id")
    own = F.struct("id", "n", "pos", "comp", *ODDS)
    met = dealt.withColumn("next", F.array(*[F.lead(own, k).over(order) for k in range(1, NEIGHBOURS + 1)]))
    good = F.filter("next", lambda y: y.isNotNull() & (y["comp"] != F.col("comp")) & may_link(_x, lambda c: y[c]))
    return met.select("id", F.explode(good).alias("y")).select(*_ordered(F.col("id"), F.col("y.id"))).distinct()


def all_pairs(lists: DataFrame) -> DataFrame:
    """Distinct pairs of documents of different groups in the lists; a pair that may reach the limit is never left out."""
    before = F.collect_list("token").over(W.partitionBy("id").orderBy("pos", "token").rowsBetween(-BEFORE, -1))
    rows = lists.withColumns({"before": before, "class": _size_class(), "parts": F.ceil(F.col("k") / BLOCK).cast("int")})
    dealt = rows.withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")).drop("parts", "k")
    # a long list's parts each meet the whole list
    meets = F.flatten(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda p: F.array(F.struct(F.col("class").alias("class"), p.alias("part")), F.struct((F.col("class") + 1).alias("class"), p.alias("part")))))
    there = rows.withColumn("at", F.explode(meets)).drop("parts", "k")
    same = (F.col("token") == F.col("p_token")) & (F.col("at.class") == F.col("p_class")) & (F.col("at.part") == F.col("p_part"))
    other = (F.col("comp") != F.col("p_comp")) & ((F.col("class") < F.col("p_class")) | (F.col("id") < F.col("p_id")))
    met = there.join(_renamed(dealt), same & other & may_link(_x, _y) & ~F.arrays_overlap("before", "p_before"))
    return met.select(*_ordered(F.col("id"), F.col("p_id"))).distinct()


def _suffix_filter(pairs: DataFrame, signatures: DataFrame) -> DataFrame:
    """pairs (a, b) whose range counts allow the overlap that the limit asks for."""
    one = signatures.select(F.col("id").alias("a"), F.col("n").alias("n_a"), F.col("sig").alias("s_a"))
    two = signatures.select(F.col("id").alias("b"), F.col("n").alias("n_b"), F.col("sig").alias("s_b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            c = {k: batch.column(k).to_pylist() for k in batch.schema.names}
            keep = [overlap_bound(x, y) * (100 + LIMIT) >= LIMIT * (n + m) for x, y, n, m in zip(c["s_a"], c["s_b"], c["n_a"], c["n_b"])]
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(one, "a").join(two, "b").mapInArrow(tidy(run), "a long, b long")


def _verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    one, two = sets.select(F.col("id").alias("a"), F.col("tokens").alias("t_a")), sets.select(F.col("id").alias("b"), F.col("tokens").alias("t_b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("t_a"), batch.column("t_b")):
                s, t = np.frombuffer(x.as_buffer(), dtype="<u8"), np.frombuffer(y.as_buffer(), dtype="<u8")
                at = np.minimum(np.searchsorted(s, t), len(s) - 1)
                both = int(np.count_nonzero(s[at] == t))
                keep.append(both * 100 >= LIMIT * (len(s) + len(t) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(one, "a").join(two, "b").select("a", "b", "t_a", "t_b").mapInArrow(tidy(run), "a long, b long")


def links(texts: DataFrame, profile: DataFrame, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """(representatives of ids that have another's set, groups of representatives as node and component); ids are of one text each."""
    spark = texts.sparkSession
    rows = profile.filter("token is null and id is not null and n > 0").select("id", "n", "c1", "c2", "sig", *ODDS)
    classes = rows.groupBy("c1", "c2").agg(F.min("id").alias("rep"), F.max("id").alias("last")).filter("rep < last").select("c1", "c2", "rep")
    copies = scratch.keep(rows.select("id", "c1", "c2").join(classes, ["c1", "c2"]).filter("id > rep").select("id", "rep").distinct(), "copies")
    frequent = spark.sparkContext.broadcast(frequent_tokens(profile))
    entries = scratch.keep(shared(postings(texts, frequent)), "shared")
    stand_in = entries.join(copies.withColumnRenamed("id", "c"), F.col("id") == F.col("c"), "left")
    # one exchange by token serves the lists, their marks and the join of both
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    lists = stand_in.select("token", F.coalesce("rep", "id").alias("id"), "n", "pos").repartition(parts, "token").groupBy("token", "id").agg(F.max("n").alias("n"), F.max("pos").alias("pos"))
    # tokens of one passage have the same documents: such lists, known by count and two hashes of their ids, are looked at once
    same = ["k", "x1", "x2"]
    # the one whose token is the first of them in every set's order stands for them
    marks = lists.groupBy(F.col("token").alias("t")).agg(F.count(F.lit(1)).alias("k"), F.min("pos").alias("p"), F.bit_xor(F.xxhash64("id")).alias("x1"), F.bit_xor(F.xxhash64(F.col("id"), F.lit(1))).alias("x2")).filter("k > 1")
    once = marks.groupBy(*same).agg(F.min(F.struct("p", "t")).alias("first")).select(F.col("first.t").alias("t"), "k")
    odd = rows.select(F.col("id").alias("i"), *ODDS).dropDuplicates(["i"])
    kept = lists.join(once, F.col("token") == F.col("t")).join(odd, F.col("id") == F.col("i"))
    lists = scratch.keep(kept.select("token", "id", "n", "pos", "k", *ODDS), "lists")
    if lists.isEmpty():
        return copies, lists.select(F.col("id").alias("node"), F.col("id").alias("component"))
    ids = lists.select(F.col("id").alias("i")).distinct()
    # signatures of documents that share a token, dealt as joins deal them
    dealt = Bucketed(scratch, "signatures", "id")
    tried = None

    def linked(pairs: DataFrame, name: str) -> DataFrame:
        """The links among the pairs that weren't tried before."""
        nonlocal tried
        pairs = scratch.keep(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), f"pairs-{name}")
        tried = pairs if tried is None else tried.unionAll(pairs)
        near = scratch.keep(_suffix_filter(pairs, signatures), f"near-{name}")
        if near.isEmpty():
            return near
        found = scratch.keep(_verify(near, scratch.keep(_packed(texts, near), f"sets-{name}")), f"links-{name}")
        scratch.drop(f"sets-{name}")
        return found

    def grouped(groups: DataFrame) -> DataFrame:
        rest = groups.filter("node <> component").select(F.col("node").alias("v"), "component")
        return lists.join(rest, F.col("id") == F.col("v"), "left").withColumn("comp", F.coalesce("component", "id")).drop("v", "component")

    def merged(found: DataFrame, groups: DataFrame, name: str) -> DataFrame:
        """Groups by these links and what was known."""
        known = groups.filter("node <> component").select(F.col("component").alias("a"), F.col("node").alias("b"))
        return components(found.unionAll(known), "a", "b", scratch, name)

    try:
        signatures = dealt.keep(rows.select("id", "n", "sig").repartition(parts, "id").join(ids.repartition(parts, "i"), F.col("id") == F.col("i"), "left_semi"))
        # two documents that have a link to the same third one are known to be of one group; most groups are whole after this
        first = linked(least_pairs(lists), "least")
        groups = scratch.keep(first.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("component")), "groups")
        for turn in range(ROUNDS):
            found = linked(neighbour_pairs(grouped(groups), turn), f"near-{turn}")
            groups = merged(found if turn else found.unionAll(first), groups, f"groups-{turn}")
            if 2 * found.count() <= spark.read.parquet(scratch.path(f"pairs-near-{turn}")).count():
                break
        now = grouped(groups)
        mixed = now.groupBy(F.col("token").alias("t")).agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("t")
        last = linked(all_pairs(now.join(mixed, F.col("token") == F.col("t"), "left_semi")), "all")
        return copies, merged(last if ROUNDS else last.unionAll(first), groups, "groups-all")
    finally:
        dealt.drop()


def told(rows: DataFrame, key: str, ids: DataFrame) -> DataFrame:
    """rows with `may`, never false where the key is among ids, a table of one column: a bit table of fixed size tells, without an exchange of rows."""
    word, bit = (lambda h: F.pmod(F.shiftright(h, 6), F.lit(WANTED))), F.expr("shiftleft(1L, cast(_h & 63 as int))")
    wanted = ids.select(F.xxhash64(F.col(ids.columns[0])).alias("_h")).groupBy(word(F.col("_h")).alias("_word")).agg(F.bit_or(bit).alias("_bits"))
    met = rows.withColumn("_h", F.xxhash64(key)).join(F.broadcast(wanted), word(F.col("_h")) == F.col("_word"), "left")
    return met.withColumn("may", F.coalesce(F.col("_bits").bitwiseAND(bit) != 0, F.lit(False))).drop("_h", "_word", "_bits")


def _packed(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """Rows (id, tokens): the whole sets, as bytes, of the ids in pairs, and of a few more whose hash is like one of theirs.

    The ids' bits in a table of fixed size pick the texts where they are read, so that texts aren't shuffled.
    """

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch):
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array([shingle_set(x).tobytes() for x in part.column("text").to_pylist()], pa.binary())], names=["id", "tokens"])

    chosen = told(texts.filter("id is not null"), "id", pairs.select("a").unionAll(pairs.select("b"))).filter("may")
    return chosen.select("id", "text").mapInArrow(tidy(pack), "id long, tokens binary").filter(F.octet_length("tokens") > 0)


def near_duplicates(docs: DataFrame, doc: str = "doc_id", text: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """Rows (doc_id, n_shingles, component_id), one for each row of docs.

    component_id is the smallest doc_id reachable over links of at least the similarity limit. Texts without words have the
    empty set and are alone; null ids have no component; rows that share a doc_id are one document, linked if any of its
    texts is, and each has a row. An empty table gives an empty one. Other columns are ignored.
    """
    scratch = scratch or Scratch(docs.sparkSession, "jaccard")
    texts = _texts(docs, doc, text)
    profile = scratch.keep(profiles(texts), "profiles")
    rows = profile.filter("token is null")
    if not rows.filter("id is not null").groupBy("id").agg(F.count_distinct("n", "c1", "c2").alias("k")).filter("k > 1").isEmpty():
        return _by_text(docs, doc, text, scratch)
    copies, groups = links(texts, profile, scratch)
    out = rows.select("id", "n").join(copies.withColumnRenamed("id", "c"), F.col("id") == F.col("c"), "left").withColumn("stands", F.coalesce("rep", "id"))
    out = out.join(groups, F.col("stands") == F.col("node"), "left")
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component", "stands").alias("component_id"))


def _by_text(docs: DataFrame, doc: str, text: str, scratch: Scratch) -> DataFrame:
    """near_duplicates() where an id has several texts: each (id, text) is grouped by itself, then ids join their groups."""
    own = F.when(F.col(f"`{doc}`").isNotNull(), F.xxhash64(f"`{doc}`", f"`{text}`"))
    each = docs.select(F.col(f"`{doc}`").alias("d"), own.alias("s"), F.col(f"`{text}`").alias("t"))
    found = scratch.keep(near_duplicates(each, "s", "t", Scratch(docs.sparkSession, "jaccard")).distinct(), "by-text")
    rows = each.select("d", "s").join(found, F.col("s").eqNullSafe(F.col("doc_id"))).filter("d is not null")
    rows = scratch.keep(rows.select("d", "s", "n_shingles", "component_id").distinct(), "rows")
    least = rows.groupBy(F.col("d").alias("e")).agg(F.min("component_id").alias("m"))
    joined = components(rows.join(least, F.col("d") == F.col("e")).select("component_id", "m"), "component_id", "m", scratch, "whole")
    whole = rows.join(joined, F.col("component_id") == F.col("node"), "left").withColumn("root", F.coalesce("component", "component_id"))
    smallest = whole.groupBy(F.col("root").alias("r")).agg(F.min("d").alias("smallest"))
    named = whole.join(smallest, F.col("root") == F.col("r")).select(F.col("s").alias("s2"), "n_shingles", "smallest").distinct()
    bare = found.filter("doc_id is null").select("n_shingles")
    out = each.join(named, F.col("s") == F.col("s2")).select(F.col("d").alias("doc_id"), "n_shingles", F.col("smallest").alias("component_id"))
    if bare.isEmpty():
        return out
    none = profiles(_texts(docs.filter(F.col(f"`{doc}`").isNull()), doc, text)).filter("token is null")
    return out.unionAll(none.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.lit(None).cast("long").alias("component_id")))
