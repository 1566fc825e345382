"""Language identification as a mixture: which languages a document holds, and how much of each.

Each language has a distribution over hashed character n-grams (lengths 1 to 4, of words in lower case with a blank at
both ends), learnt by counting with additive smoothing. A document's n-grams are taken as drawn from a mixture of the
languages; expectation-maximisation finds the shares. The set of languages is the one of the nested sets by share whose
log-likelihood, less half a logarithm of the evidence for each further language, is the largest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from floorcount.llm.scratch import free_name, must_be_free, tidy

#: Cells that n-grams are hashed to, for each language: the model's size is fixed by this and MAX_LANGUAGES. Of more labels,
#: the most frequent are learnt, and documents in others are given the likeliest of these.
CELLS = 1 << 15
MAX_LANGUAGES = 200
#: Texts for each language that the model is fitted on, about; chosen by a hash of text. Counting more changes little.
SAMPLE_TEXTS = 4_000
SMOOTHING = 0.5
ROUNDS, SETTLED = 30, 1e-3
#: N-grams of one text overlap, so a further language must explain this many times its penalty.
EVIDENCE = 8.0
UNKNOWN = "und"
LETTER = regex.compile(r"\p{L}").search
_PRIMES = np.array([0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35, 0x27D4EB2F], dtype=np.uint64)


def _letter_table() -> np.ndarray:
    """Code point to itself in lower case if it is a letter, else to a blank; for the first plane."""
    table = np.full(0x10000, 32, dtype=np.uint32)
    for c in range(0x10000):
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            table[c] = ord(low) if len(low) == 1 else c
    return table


_table: list[np.ndarray] = []


def gram_cells(text: str) -> np.ndarray:
    """The cells of all n-grams of a text, with repeats."""
    if not _table:
        _table.append(_letter_table())
    code = np.frombuffer(f" {text} ".encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    c = np.where(code < 0x10000, _table[0][np.minimum(code, 0xFFFF)], code).astype(np.uint64)
    keep = np.ones(len(c), dtype=bool)
    keep[1:] = (c[1:] != 32) | (c[:-1] != 32)
    c = c[keep]
    cells = []
    for width in (1, 2, 3, 4):
        n = len(c) - width + 1
        if n <= 0:
            break
        h = np.full(n, width, dtype=np.uint64)
        for k in range(width):
            h = (h * np.uint64(31) + c[k : k + n]) * _PRIMES[k] & np.uint64(0xFFFFFFFFFFFF)
        inner = np.zeros(n, dtype=bool)  # n-grams across words say little about either
        for k in range(1, width - 1):
            inner |= c[k : k + n] == 32
        h = (h ^ (h >> np.uint64(17))) * _PRIMES[1]
        cells.append(((h >> np.uint64(11)) % np.uint64(CELLS))[~inner])
    return np.concatenate(cells).astype(np.int64) if cells else np.empty(0, dtype=np.int64)


def learn(labelled: DataFrame, text: str = "text", lang: str = "lang") -> tuple[list[str], np.ndarray]:
    """Languages and their probabilities, a float32 array (CELLS, languages), from rows with a text and a language."""
    rows = labelled.select(F.col(f"`{lang}`").cast("string").alias("lang"), F.col(f"`{text}`").cast("string").alias("text")).dropna()
    size = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(MAX_LANGUAGES).collect()
    if not size:
        return [], np.zeros((CELLS, 0), dtype=np.float32)
    share = F.create_map(*[F.lit(x) for r in size for x in (r["lang"], int(min(1.0, SAMPLE_TEXTS / r["n"]) * 1_000_000))])
    sample = rows.filter(F.pmod(F.xxhash64("text"), F.lit(1_000_000)) < F.try_element_at(share, F.col("lang")))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for name, body in zip(batch.column("lang").to_pylist(), (x.decode("utf-8", "replace") for x in batch.column("text").cast(pa.binary()).to_pylist())):
                held = total.setdefault(name, np.zeros(CELLS, dtype=np.int64))
                held += np.bincount(gram_cells(body), minlength=CELLS)
        for name, held in total.items():
            at = np.flatnonzero(held)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at, pa.int64()), pa.array(held[at], pa.int64())], names=["lang", "cell", "n"])

    table = sample.mapInArrow(tidy(count), "lang string, cell long, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n")).toArrow()
    names = sorted(r["lang"] for r in size)
    counts = np.zeros((CELLS, len(names)))
    place = {n: i for i, n in enumerate(names)}
    counts[table.column("cell").to_numpy(), [place[x] for x in table.column("lang").to_pylist()]] = table.column("n").to_numpy()
    counts += SMOOTHING
    return names, (counts / counts.sum(axis=0)).astype(np.float32)


def mixture(p: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, float]:
    """Shares of the columns of p that make the weighted rows most likely, and that log-likelihood."""
    share = np.full(p.shape[1], 1.0 / p.shape[1])
    total = weight.sum()
    for _ in range(ROUNDS):
        joint = p * share
        mix = joint.sum(axis=1)
        fresh = (weight / mix) @ joint / total
        moved = np.abs(fresh - share).max()
        share = fresh
        if moved < SETTLED:
            break
    return share, float(weight @ np.log(p @ share))


def identify(text: str | None, names: list[str], p: np.ndarray) -> tuple[str, float, list[tuple[str, float]]]:
    """Main language, its share, and the chosen languages with their shares, the largest first."""
    if not text or not names or not LETTER(text):
        return UNKNOWN, 0.0, []
    cells, weight = np.unique(gram_cells(text), return_counts=True)
    rows, weight = p[cells].astype(np.float64), weight.astype(np.float64)
    share, _ = mixture(rows, weight)
    order = np.argsort(-share, kind="stable")
    best, kept = None, None
    penalty = 0.5 * EVIDENCE * np.log(weight.sum() + 1)
    for k in range(1, len(names) + 1):
        if k > 1 and share[order[k - 1]] < 0.02:
            break
        some = order[:k]
        part, like = (np.ones(1), float(weight @ np.log(rows[:, some[0]]))) if k == 1 else mixture(rows[:, some], weight)
        value = like - penalty * (k - 1)
        if best is not None and value <= best:
            break
        best, kept = value, sorted(zip((names[i] for i in some), part.tolist()), key=lambda x: (-x[1], x[0]))
    return kept[0][0], min(1.0, kept[0][1]), kept


def predict(df: DataFrame, model: Broadcast, text: str = "text", to: str = "language") -> DataFrame:
    """df without the text, with a struct `to`: main, score, and languages as an array of (lang, share)."""
    kind = f"struct<main: string, score: double, languages: array<struct<lang: string, share: double>>>"
    rest = [f for f in df.schema.fields if f.name != text]
    given = df.select(*[F.col(f"`{f.name}`") for f in rest], F.col(f"`{text}`").cast("string").alias(free_name(df, "_text")))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rest), f"`{to}` {kind}"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, p = model.value
        out = pa.struct([("main", pa.string()), ("score", pa.float64()), ("languages", pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())])))])
        for batch in batches:
            found = []
            for body in batch.column(batch.num_columns - 1).cast(pa.binary()).to_pylist():
                main, score, languages = identify(None if body is None else body.decode("utf-8", "replace"), names, p)
                found.append({"main": main, "score": score, "languages": [{"lang": a, "share": b} for a, b in languages]})
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, out)], names=[f.name for f in rest] + [to])

    return given.mapInArrow(tidy(run), schema)


def held_out(doc: Column) -> Column:
    """Documents that nothing is learnt from: crc32 of the id as text leaves 1 when divided by 3."""
    return F.coalesce(F.crc32(doc.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def identify_languages(df: DataFrame, doc: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """df without the text, with `held_out` and the struct `language` of predict().

    Learns from rows that aren't held out and have a language and a text. Null texts, and texts without a letter, are `und`
    with score 0, as all are where nothing could be learnt. A null id is not held out. Repeated rows count as often as they
    come. Columns named held_out and language must not be there.
    """
    must_be_free(df, "held_out", "language")
    marked = df.withColumn("held_out", held_out(F.col(f"`{doc}`")))
    model = df.sparkSession.sparkContext.broadcast(learn(marked.filter(~F.col("held_out")), text, lang))
    return predict(marked, model, text)
