"""Each operator against a brute-force version or a round trip, on texts that are hard to get right."""

import hashlib
import random
import re
import struct

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from floorcount.llm import byte_bpe, components, decontamination, jaccard_join, language_mix, legacy_archive, license_scan, line_winnow, quality_rules, token_rollups, url_aliases
from floorcount.llm.scratch import Scratch
from tests_llm_prose import prose

EDGE = [None, "", " ", "\n", "a", "  \n\t ", "word " * 5, prose(1, 30_000), prose(2, 60), prose(2, 60), "é漢字🎉 " * 12, "\x00\x1f x", "a\r\nb\x0bc d"]


def white(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def lower(text):
    return "".join(c.lower() if c < "\x80" else c for c in text or "")


# --- quality rules -------------------------------------------------------------------------------------------------


def measured(text):
    w, t = white(text), text or ""
    where = {}
    for i in range(len(w) - 7):
        where.setdefault(tuple(w[i : i + 8]), []).append(i)
    hit = {i + k for v in where.values() if len(v) > 1 for i in v for k in range(8)}
    lines = [x for x in t.split("\n") if white(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(hit), len(lines)


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet="ab \n\t#é ", max_size=120))
def test_measures(text):
    assert quality_rules.measure_text(text.encode()) == measured(text)


def test_quality_judges_each_row(docs_of, spark):
    junk = [" ".join(f"{w}%%%" for w in prose(i, 60).split()) for i in range(3)]
    df = docs_of([*EDGE, *[prose(f"good{i}", 80) for i in range(150)], *junk])
    out = quality_rules.judge(df).collect()
    assert len(out) == df.count() and {"g", "lang", "source", "n_chars"} <= set(out[0].asDict())
    by = {r["doc_id"]: r for r in out}
    assert all(by[i]["base_failed"] and not by[i]["kept"] for i in (0, 1, 2, 3, 4, 5, 6))
    n = len(EDGE)
    assert all(by[i]["kept"] for i in range(n, n + 150)) and all(by[n + 150 + i]["beyond"] for i in range(3))
    assert quality_rules.judge(df.limit(0)).count() == 0
    kept = quality_rules.judge(df, keep_text=True)
    assert sorted(map(str, kept.select("doc_id", "kept").collect())) == sorted(map(str, [r for r in quality_rules.judge(df).select("doc_id", "kept").collect()])) and "text" in kept.columns
    with pytest.raises(ValueError):
        quality_rules.judge(df.withColumn("kept", F.lit(1)))


def test_junk_sets_no_threshold_for_itself(spark):
    """A source of a third of all rows, half of them symbol junk, and a source of junk alone are judged as their neighbours are."""
    junk = lambda i: " ".join(f"{w}%%" for w in prose(f"junk{i}", 30).split())
    rows = [(1000 * s + i, prose(f"fine{s}-{i}", 30), "en", f"s{s}") for s in range(4) for i in range(110)]
    spam = [(10_000 + i, junk(i) if i % 2 else prose(f"spam{i}", 30), "en", "spam") for i in range(220)]
    rows += spam + [(20_000 + i, junk(i), "en", "junk") for i in range(110)] + [(30_000, junk(1), "en", "s0")]
    out = {r["doc_id"]: r for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    for i, text, _, _ in rows:
        assert out[i]["kept"] == ("%" not in text) and ("symbols" in out[i]["beyond"]) == ("%" in text)


def test_fences_are_planned_in_small_steps(docs_of, spark, monkeypatch):
    """The driver holds each plan as text, again and again: what is written at once has few exchanges."""
    seen, keep = {}, Scratch.keep

    def told(self, df, name, *rest):
        seen[name] = df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
        return keep(self, df, name, *rest)

    monkeypatch.setattr(Scratch, "keep", told)
    df = docs_of([prose(f"planned{i}", 30) for i in range(20)])
    assert quality_rules.judge(df, keep_text=True).filter("kept").count() >= 20
    assert "fences" in seen and max(seen.values()) <= 12


def test_buckets_rise_and_keep_small_numbers(spark):
    got = [r["b"] for r in spark.range(5000).orderBy("id").select(quality_rules.bucket(F.col("id")).alias("b")).collect()]
    assert got[:64] == list(range(64)) and got == sorted(got) and got == [quality_rules._bucket(i) for i in range(5000)]


# --- decontamination -----------------------------------------------------------------------------------------------


def bare(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))


def contamination(text, items):
    w, hit, found = bare(text), set(), set()
    for item, body in items:
        b = bare(body)
        if item is None or not b:
            continue
        n = min(13, len(b))
        for win in {tuple(b[i : i + n]) for i in range(max(1, len(b) - 12))}:
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) == win:
                    hit |= set(range(i, i + n))
                    found.add(str(item))
    return len(w), len(hit), sorted(found)


@pytest.mark.parametrize("block", [8_000_000, 300])
def test_contamination_equals_brute_force(docs_of, spark, block, monkeypatch):
    monkeypatch.setattr(decontamination, "BLOCK_BYTES", block)
    items = [(10, prose("q", 20)), (9, prose("short", 3)), (2, prose("q", 20)), (None, prose("r", 15)), (3, None), (4, ""), (5, "Ab é-x")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    q = prose("q", 20).split()
    texts = [*EDGE, "x, " + ", ".join(q).upper() + "!", " ".join(q[:12]), " ".join(q[3:17]) + " z", "pre " + prose("short", 3) + " post", "ab é x", "xab é x", " ".join(q + q)]
    df = docs_of(texts)
    out = decontamination.scan(df, bench).select("doc_id", "text", "found", decontamination.n_hit().alias("n")).collect()
    assert len(out) == df.count()
    for r in out:
        n, hit, found = contamination(r["text"], items)
        assert (r["found"]["n_words"], r["n"], r["found"]["items"]) == (n, hit, found), r["text"]
        for a, b in ((s["start"], s["end"]) for s in r["found"]["spans"]):
            assert bare(r["text"][a:b]) and re.match(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]", r["text"][a])
    empty = decontamination.scan(df, bench.limit(0))
    assert empty.filter(F.size("found.items") > 0).count() == 0 and decontamination.scan(df.limit(0), bench).count() == 0


class Sent:
    def __init__(self, value):
        self.value = value


def test_a_dropped_benchmark_leaves_no_automaton_to_another():
    for i in range(30):  # each list may take the address of the one before
        pack = getattr(decontamination, "named", lambda x: x)
        assert decontamination.built(Sent(pack([(f"item{i}".encode(), str(i))]))).find(f"an item{i} here".encode())[3] == [str(i)]


# --- archives ------------------------------------------------------------------------------------------------------


def test_archive_round_trip(spark):
    body = "<p>" + prose("page", 40)
    rows = [(5, "http://a/b c", body), (3, None, body), (9, "http://x\r\ny", "small"), (1, "http://s", "small"), (7, "", None), (None, "http://n", body), (2, "http://w", "HTTP/1.1 200\r\n\r\nWARC/1.1\r\n\r\n" * 20), (3, None, body)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("archive", F.lit("clash"))
    out = legacy_archive.archive_pages(pages).collect()
    assert len(out) == len(rows) and all(r["intact"] for r in out)
    for r in out:
        assert r["payload_digest"] in {hashlib.sha256((h or "").encode()).hexdigest() for _, _, h in rows}
    big = [r for r in out if r["payload_digest"] == hashlib.sha256(body.encode()).hexdigest()]
    assert [r["page_id"] for r in big if r["record_type"] == "response"] == [3] and all(r["refers_to"] == 3 for r in big if r["record_type"] == "revisit") and len(big) == 4
    assert all(r["record_type"] == "response" and r["refers_to"] is None for r in out if r not in big)
    assert legacy_archive.archive_pages(pages.limit(0)).count() == 0


def test_arc_lines_of_both_versions_and_across_chunks():
    blocks = [b"HTTP/1.0 200 OK\r\nA: b\r\n\r\nhello\nhttp://x 1 2 3 4\n", b"", b"no header"]
    for version in (1, 2):
        data = legacy_archive.arc_version_record(version, "n.arc", "2001") + b"".join(legacy_archive.arc_record(version, f"http://h/{i} q", "20010203040506", b, 7, "n.arc") for i, b in enumerate(blocks))
        for size in (1, 7, 10_000):
            got = list(legacy_archive.parse_arc(data[i : i + size] for i in range(0, len(data), size)))
            assert [g[2] for g in got] == blocks and [g[1]["URL"] for g in got] == [f"http://h/{i} q" for i in range(3)]
    assert legacy_archive.warc_time("20010203040506") == "2001-02-03T04:05:06Z" and legacy_archive.warc_type("http://a", blocks[2]) == "resource"
    with pytest.raises(ValueError):
        list(legacy_archive.parse_arc([b"http://a 0 2001 text/html 99\nshort"]))


def test_pages_that_look_like_version_records_stay(spark):
    body = "1 0 floorcount\nURL IP-address\n" + prose("odd", 30)
    rows = [(1, "filedesc://a.arc 0.0.0.0 2001 text/plain 12", body), (2, "filedesc://b", "2 0 x\nURL Archive-length\n"), (3, "filedesc://", None), (4, "metadata://m", body)]
    scratch = legacy_archive.Scratch(spark, "odd")
    out = {r["page_id"]: r for r in legacy_archive.archive_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), scratch).collect()}
    assert sorted(out) == [1, 2, 3, 4] and all(r["intact"] for r in out.values())
    assert {i: out[i]["url"] for i in out} == {i: u for i, u, _ in rows} and out[4]["refers_to"] == 1
    about = [r for r in legacy_archive.read_warc(spark, scratch.path("warc")).collect() if r["record_type"] == "warcinfo"]
    assert about and all(r["intact"] and r["url"] is None and r["page_id"] is None for r in about)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.one_of(st.none(), st.text(st.characters(exclude_categories=["Cs"]), max_size=30), st.sampled_from(["filedesc://x", "filedesc://x 1 2 3 4", " ", "-"])), st.binary(max_size=80)), max_size=6), st.sampled_from([1, 2]), st.integers(1, 50))
def test_any_url_and_block_come_back(records, version, step):
    data, places = legacy_archive.arc_version_record(version, "n.arc", "2001"), []
    for url, block in records:
        places.append(len(data))
        data += legacy_archive.arc_record(version, url, "20010203040506", legacy_archive.http_block(7, block), 0, "n.arc")
    got = list(legacy_archive.parse_arc(data[i : i + step] for i in range(0, len(data), step)))
    assert [legacy_archive.split_http(g[2])[1] for g in got] == [b for _, b in records] and [g[0] for g in got] == places
    assert [g[1]["URL"] for g in got] == [((u if u is not None else "-").replace("\r", "%0D").replace("\n", "%0A") or "-") for u, _ in records]


# --- byte-level BPE ------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def coders():
    import tiktoken

    ranks = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    return byte_bpe.ByteBpe(ranks, public_tokenizers.PATTERN), tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def ids(packed):
    return list(struct.unpack(f"<{len(packed) // 4}I", packed))


@settings(max_examples=400, deadline=None)
@given(text=st.one_of(st.text(max_size=60), st.text(alphabet=" \n\t'sdmltrevab1.,!  \x1cé", max_size=40)))
def test_bpe_equals_the_library(coders, text):
    ours, theirs = coders
    assert ids(ours.encode(text)) == theirs.encode_ordinary(text) and ours.decode(ours.encode(text)) == text.encode()


def test_bpe_tells_neighbours_without_merging(coders):
    ours = coders[0]
    rank = np.random.default_rng(7).integers(0, len(ours.tokens), (4000, 2)).tolist() + [[r, r] for r in range(0, 3000, 7)]
    for word in (" undenominational", " zzzzzzzzz", " ththethin", " aaaaaaaa", " cimenteadoqueja"):
        made = ours.encode_piece(word.encode())
        rank += [list(x) for x in zip(made, made[1:])] + [[made[0], r] for r in made]
    for left, right in rank:
        if ours.tokens[left] and ours.tokens[right] and all(ours.merged(ours.tokens[x]) == [x] for x in (left, right)):
            assert ours.stay_apart(left, right) == (ours.merged(ours.tokens[left] + ours.tokens[right]) == [left, right])
    rows = [None, b"", np.array(made, dtype="<u4").tobytes(), b"", np.array(made[:1], dtype="<u4").tobytes()]
    for first in range(5):
        assert ours.decode_all(pa.array(rows, pa.binary()).slice(first)).to_pylist() == [ours.decode(x) for x in rows[first:]]
    assert ours.decode_all(pa.array([], pa.binary())).to_pylist() == []


def test_bpe_of_columns(docs_of, coders, spark):
    df = docs_of([*EDGE, "a" * 3000, "é" * 500])
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    both = byte_bpe.decode(byte_bpe.encode(df, path, public_tokenizers.PATTERN), path, public_tokenizers.PATTERN)
    out = both.withColumn("list", byte_bpe.id_array(F.col("token_ids"))).collect()
    assert len(out) == df.count()
    for r in out:
        assert r["list"] == coders[1].encode_ordinary(r["text"] or "") == ids(bytes(r["token_ids"])) and bytes(r["decoded"]) == (r["text"] or "").encode()
    assert byte_bpe.encode(df.limit(0), path, public_tokenizers.PATTERN).count() == 0


def test_round_trip_equals_both_calls_in_one_pass(docs_of, spark):
    import corpus_pipeline

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    df = docs_of([*EDGE, "a" * 3000, "é" * 500])
    once = byte_bpe.round_trip(df, path, public_tokenizers.PATTERN)
    both = byte_bpe.decode(byte_bpe.encode(df, path, public_tokenizers.PATTERN), path, public_tokenizers.PATTERN)
    assert once.columns == both.columns and sorted(map(str, once.collect())) == sorted(map(str, both.collect()))
    stage = corpus_pipeline.tokenize(spark, df.select("doc_id", "text"), "")
    assert stage._jdf.queryExecution().executedPlan().toString().count("MapInArrow ") == 1
    with pytest.raises(ValueError):
        byte_bpe.round_trip(df.withColumn("DECODED", F.lit(1)), path, public_tokenizers.PATTERN)


# --- languages -----------------------------------------------------------------------------------------------------


def test_languages_on_held_out_documents(spark):
    found = language_mix.identify_languages(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"))
    rows = found.filter("held_out").select("lang", "language.main").collect()
    assert sum(r["lang"] == r["main"] for r in rows) / len(rows) > 0.98


def test_language_edges_and_mixtures(docs_of, spark):
    d = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    long = {r["lang"]: r["text"] for r in d.filter("length(text) > 3000").collect()}
    mix = spark.createDataFrame([(1_000_000 + i, t, None) for i, t in enumerate([None, "", "123 ...", long["en"][:3000] + " " + long["fr"][:3000]])], d.schema)
    out = {r["doc_id"]: r["language"] for r in language_mix.identify_languages(d.unionAll(mix)).filter("doc_id >= 1000000").collect()}
    assert all(out[1_000_000 + i]["main"] == "und" and out[1_000_000 + i]["score"] == 0 for i in range(3))
    assert {x["lang"] for x in out[1_000_003]["languages"]} == {"en", "fr"} and all(0.3 < x["share"] < 0.7 for x in out[1_000_003]["languages"])
    nothing = language_mix.identify_languages(docs_of(EDGE).withColumn("lang", F.lit(None).cast("string")))
    assert nothing.filter("language.main <> 'und'").count() == 0 and language_mix.identify_languages(d.limit(0)).count() == 0


# --- line dedup ----------------------------------------------------------------------------------------------------


def test_passages_go_once_and_clean_lines_stay(docs_of, spark):
    p, own = [prose(f"p{i}", n) for i, n in enumerate((51, 9, 12, 8, 30))], lambda k: prose(f"own{k}", 31)
    texts = [f"{own(1)}\n{p[0]}\n{own(2)}", f"{p[0]}\n{own(3)}\nshort line", f"{own(4)}\n\n{p[1]}\n{p[2]}\n{p[3]}\n{p[4]}\n{own(5)}", f"short line\n{p[1]}\n\n{p[2]}\n{p[3]}\n{p[4]}\n{own(6)}", None, "", "short line", f"{own(7)}\n{own(7)}\n{own(7)}", own(8), own(8)]
    df = docs_of(texts)
    out = {r["doc_id"]: r for r in line_winnow.dedup_lines(df).filter("doc_id is not null").collect()}
    got = {k: r["text"] for k, r in out.items()}
    assert got[0] == texts[0] and got[1] == f"{own(3)}\nshort line" and got[2] == texts[2] and got[3] == f"short line\n{own(6)}"
    assert got[4] is None and got[5] == "" and got[6] == "short line" and got[7] == own(7) and got[8] == own(8) and got[9] == ""
    assert line_winnow.dedup_lines(df).count() == df.count() and line_winnow.dedup_lines(df.limit(0)).count() == 0
    plan = line_winnow.dedup_lines(df)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_every_long_run_is_found(docs_of, spark):
    """Runs of 50 words or more that two documents share, in lines of any length, lose their later copy."""
    rng = random.Random(4)
    texts = []
    for k in range(40):
        run = [prose(f"run{k}-{i}", rng.randint(1, 12)) for i in range(40)]
        while sum(len(x.split()) for x in run[:-1]) >= 50:
            run.pop()
        pad = lambda s: [prose(f"pad{k}{s}{i}", rng.randint(1, 40)) for i in range(rng.randint(0, 4))]
        texts += ["\n".join([*pad("a"), *run, *pad("b")]), "\n".join([*pad("c"), *run, *pad("d")])]
    out = {r["doc_id"]: r for r in line_winnow.dedup_lines(docs_of(texts, extra=False)).collect()}
    for k in range(0, 80, 2):
        assert out[k]["text"] == texts[k]
        shared = set(texts[k].split("\n")) & set(texts[k + 1].split("\n"))
        assert not shared & set(out[k + 1]["text"].split("\n"))
        assert set(texts[k + 1].split("\n")) - shared <= set(out[k + 1]["text"].split("\n"))


def test_runs_go_to_their_ends_past_long_lines(docs_of):
    """Copies with lines of 100 words and more and short last lines: nothing stays of an exact copy, nor of a run inside other text."""
    rng = random.Random(7)
    sizes = [[30, 120, 10], [9, 101, 24], [150, 3], [12, 200, 8, 8, 8], [5, 20, 110, 20], *[[rng.choice((3, 9, 24, 60, 100, 180)) for _ in range(rng.randint(2, 6))] for _ in range(25)]]
    texts = []
    for k, size in enumerate(s for s in sizes if sum(s) >= 50):
        run = [prose(f"long{k}-{i}", n) for i, n in enumerate(size)]
        texts += ["\n".join(run), "\n".join(run), "\n".join([prose(f"a{k}", 20), *run, prose(f"b{k}", 20)])]
    out = {r["doc_id"]: r["text"] for r in line_winnow.dedup_lines(docs_of(texts, extra=False)).collect()}
    for k in range(0, len(texts), 3):
        lines = texts[k + 2].split("\n")
        assert out[k] == texts[k] and out[k + 1] == "" and out[k + 2] == f"{lines[0]}\n{lines[-1]}"


def test_longer_runs_around_a_common_line_go(docs_of):
    """A line that many documents share hides no longer run around it that stands earlier than its copy."""
    hot = prose("hot", 60)
    texts = [f"{prose('owner', 30)}\n{hot}"]
    for k in range(20):
        around = f"{prose(f'u{k}', 24)}\n{hot}\n{prose(f'v{k}', 15)}\n{prose(f'w{k}', 9)}"
        texts += [around, around]
    out = {r["doc_id"]: r["text"] for r in line_winnow.dedup_lines(docs_of(texts, extra=False)).collect()}
    assert out[0] == texts[0]
    for k in range(1, len(texts), 2):
        assert out[k] == texts[k].replace(f"{hot}\n", "") and out[k + 1] == ""


def lines_left(rows, least=25):
    """Texts without every line that lies in a stretch of at least `least` words that stands earlier, by trying all stretches of all texts."""
    order = sorted({(i is None, i or 0, hashlib.md5(t.encode()).hexdigest(), t) for i, t in rows if t is not None})
    first, stretches = {}, []
    for place, (*_, t) in enumerate(order):
        lines = [(n, x, len(white(x))) for n, x in enumerate(t.split("\n")) if white(x)]
        for a in range(len(lines)):
            words = 0
            for b in range(a, len(lines)):
                words += lines[b][2]
                if words >= least:
                    run = tuple(x for _, x, _ in lines[a : b + 1])
                    first[run] = min(first.get(run, (place, a)), (place, a))
                    stretches.append((place, a, lines[a][0], lines[b][0], run))
    gone = {}
    for place, a, top, end, run in stretches:
        if first[run] < (place, a):
            gone.setdefault(place, set()).update(range(top, end + 1))
    for place, (*_, t) in enumerate(order):  # lines without words go with those before and after them
        last, bare = False, []
        for n, x in enumerate(t.split("\n")):
            if not white(x):
                bare.append(n)
                continue
            now = n in gone.get(place, ())
            if now and last:
                gone[place].update(bare)
            last, bare = now, []
    return {(None if none else i, t): "\n".join(x for n, x in enumerate(t.split("\n")) if n not in gone.get(place, ())) for place, (none, i, _, t) in enumerate(order)}


@pytest.mark.parametrize("seed", range(3))
def test_lines_left_equal_brute_force(docs_of, seed):
    """Many documents that hold parts of the same passages in several orders, with longer runs around parts that others share."""
    rng = random.Random(seed)
    pool = [prose(f"l{seed}-{i}", rng.choice((1, 2, 5, 9, 14, 24, 25, 26, 60))) for i in range(25)]
    texts = []
    for k in range(60):
        out = []
        while len(out) < rng.randint(1, 12):
            at, n = rng.randrange(len(pool)), rng.randint(1, 6)
            out += pool[at : at + n]
            if rng.random() < 0.4:
                out.append(rng.choice(["", "  ", prose(f"own{seed}{k}{len(out)}", rng.randint(1, 30))]))
        texts.append("\n".join(out))
    middle, run = prose("middle", 25), [prose(f"around{i}", 13) for i in range(2)]
    texts += [middle, *(f"{prose(f'x{i}', 9)}\n{run[0]}\n{middle}\n{run[1]}\n{prose(f'y{i}', 9)}" for i in range(8)), None, "", *EDGE]
    df = docs_of(texts)
    want = lines_left([(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()])
    for r in line_winnow.dedup_lines(df.withColumn("given", F.col("text"))).collect():
        assert r["text"] == (None if r["given"] is None else want[r["doc_id"], r["given"]])


# --- near duplicates -----------------------------------------------------------------------------------------------


def brute_groups(texts):
    sets = {}
    for i, t in texts.items():
        w = white(lower(t))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    keys = sorted(sets)
    for x, a in enumerate(keys):
        for b in keys[x + 1 :]:
            k = len(sets[a] & sets[b])
            if k and 100 * k >= 75 * (len(sets[a]) + len(sets[b]) - k):
                u, v = root(a), root(b)
                parent[max(u, v)] = min(u, v)
    return {i: (len(sets[i]), root(i)) for i in sets}


def test_lists_hold_what_may_link_and_sets_are_of_pairs_only(spark):
    rng = random.Random(4)
    rows = {(t, i): (n := rng.randint(5, 60), rng.randrange(jaccard_join.prefix_length(n))) for t in range(60) for i in rng.sample(range(50), rng.randint(1, 5))}
    rows |= {(99, 1): (10, 0), (99, 2): (14, 0), (98, 1): (20, 0), (98, 2): (21, 4)}
    df = spark.createDataFrame([(t, i, *x, False) for (t, i), x in rows.items()], "token long, id long, n int, pos int, often boolean")
    kept = {(r["token"], r["id"]) for r in jaccard_join.shared(df).collect()}
    for (t, i), (n, p) in rows.items():
        for (u, j), (m, q) in rows.items():
            if t == u and i != j and min(n, m) * 100 >= max(n, m) * 75 and min(n - p, m - q) * 175 >= (n + m) * 75:
                assert (t, i) in kept
    assert not {(99, 1), (99, 2)} & kept
    texts = spark.createDataFrame([(i, f"{prose(f'own{i}', 30)}".encode()) for i in range(300)], "id long, text binary")
    got = {r["id"]: bytes(r["tokens"]) for r in jaccard_join._packed(texts, spark.createDataFrame([(1, 7), (7, 9)], "a long, b long")).collect()}
    assert {1, 7, 9} <= set(got) and len(got) < 10 and all(t == jaccard_join.shingle_set(prose(f"own{i}", 30).encode()).tobytes() for i, t in got.items())


@pytest.mark.parametrize("rounds, block, early", [(3, 4096, 4), (0, 3, 0), (1, 5, 1)])
def test_groups_equal_brute_force(docs_of, rounds, block, early, monkeypatch):
    monkeypatch.setattr(jaccard_join, "ROUNDS", rounds)
    monkeypatch.setattr(jaccard_join, "BLOCK", block)
    monkeypatch.setattr(jaccard_join, "EARLY", early)
    monkeypatch.setattr(jaccard_join, "BEFORE", 1 + early)
    rng = random.Random(9)
    texts = list(EDGE)
    for base in range(4):
        words = prose(f"base{base}", 70).split()
        for _ in range(7):
            w = list(words)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = f"new{rng.random()}"
            texts.append(" ".join(w[rng.randint(0, 4) :]).upper())
    passage = prose("passage", 40)
    texts += [f"{prose(f'front{i}', rng.randint(1, 25))} {passage}" for i in range(12)] + [passage, passage.replace(" ", "\n")]
    df = docs_of(texts)
    out = [r for r in jaccard_join.near_duplicates(df).collect()]
    assert len(out) == df.count()
    want = brute_groups(dict(enumerate(texts)))
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in out if r["doc_id"] is not None} == want
    assert [r["component_id"] for r in out if r["doc_id"] is None] == [None]


def test_one_id_with_two_texts_links_both(spark):
    a, b = prose("a", 40), prose("b", 40)
    df = spark.createDataFrame([(5, a), (5, b), (7, a), (9, b), (1, prose("c", 40))], "doc_id long, text string")
    got = sorted((r["doc_id"], r["component_id"]) for r in jaccard_join.near_duplicates(df).collect())
    assert got == [(1, 1), (5, 5), (5, 5), (7, 5), (9, 5)] and jaccard_join.near_duplicates(df.limit(0)).count() == 0


def test_bounds_never_fall_below_the_overlap():
    for i in range(30):
        a = jaccard_join.shingle_set((prose(f"s{i}", 20 + 40 * i) + prose("t", 100)).encode())
        b = jaccard_join.shingle_set((prose(f"u{i}", 300) + prose("t", 100)).encode())
        assert jaccard_join.overlap_bound(jaccard_join.ranges(a), jaccard_join.ranges(b)) >= len(set(a.tolist()) & set(b.tolist()))


def test_components(spark):
    rng = random.Random(2)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(i, i + 1) for i in range(400, 460)] + [(500, i) for i in range(501, 560)] + [(7, None), (8, 8)]
    parent = {}

    def root(i):
        while parent.setdefault(i, i) != i:
            i = parent[i]
        return i

    for a, b in pairs:
        if b is not None and a != b:
            u, v = root(a), root(b)
            parent[max(u, v)] = min(u, v)
    df = spark.createDataFrame(pairs, "a long, b long")
    got = {r["node"]: r["component"] for r in components.components(df, "a", "b", Scratch(spark)).collect()}
    assert got == {i: root(i) for i in parent} and components.components(df.limit(0), "a", "b", Scratch(spark)).count() == 0


# --- URLs ----------------------------------------------------------------------------------------------------------


def test_verdicts_reach_aliases(spark):
    link = lambda u: f'<html><head><link rel="canonical" href="{u}"></head>'
    move = lambda u: f"<meta http-equiv='refresh' content='0; url={u}'>"
    rows = [
        (1, "http://bad.com/de/1", None), (2, "http://mirror.net/a", link("http://bad.com/de/1")), (3, "https://www.mirror.net/a/#x", ""), (4, "http://ok.org/x", link("http://mirror.net/a")),
        (5, "http://far.net/z?utm_source=q&k=1", move("http://example.org/en/15")), (6, "http://far.net/z?k=1", ""), (7, None, link("http://bad.com/de/1")), (8, "no scheme", None), (9, "HTTP://Sub.Example.ORG/es/q?x#y", ""), (10, "http://borg/", ""), (11, "http://org", ""), (2, "http://mirror.net/a", link("http://bad.com/de/1")),
    ]
    out = url_aliases.judge_urls(spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 AS node", "1 AS passed", "1 AS _own", "1 AS _node", "1 AS a")).collect()
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in out}
    assert len(out) == len(rows)
    assert got[1] == ("bad.com", "/de/1", "com/de/", "block") and got[4][2:] == ("org/", "allow")
    assert got[2][3] == "allow" and got[3][3] == "allow"  # an explicit allow in the component comes before the block
    assert got[5][2:] == (None, "block") and got[6][2:] == (None, "block")
    assert got[7] == ("", "", None, "allow") and got[8] == ("", "", None, "allow")
    assert got[9] == ("sub.example.org", "/es/q", "example.org/es/", "block") and got[10][2] is None and got[11] == ("org", "", None, "allow")
    redirects = spark.createDataFrame([("http://solo.net/", "http://bad.com/de/7"), (None, "x")], "source string, target string")
    pages = spark.createDataFrame([(1, "https://solo.net", "")], "page_id long, url string, html string")
    assert url_aliases.judge_urls(pages, redirects).first()["verdict"] == "block" and url_aliases.judge_urls(pages.limit(0)).count() == 0


# --- rollups -------------------------------------------------------------------------------------------------------


def test_rollups_follow_inserts_revisions_and_deletes_once(spark):
    rollup = token_rollups.Rollup(spark, Scratch(spark, "t").path("state"))
    schema = "op string, doc_id long, source string, lang string, tokenizer string, n_tokens long, seq int"
    batch = lambda *rows: spark.createDataFrame(list(rows), schema)
    totals = lambda: sorted((r["source"] or "", r["lang"] or "", r["n_docs"], r["n_tokens"]) for r in rollup.totals().collect())
    assert totals() == []
    one = batch(("insert", 1, "a", "en", "t", 10, 0), ("insert", 2, "a", None, "t", 20, 0), ("insert", 3, None, "en", "t", None, 0), ("insert", 1, "a", "en", "t", 7, 1))
    assert rollup.commit("b1", one) and not rollup.commit("b1", one)
    assert totals() == [("", "en", 1, 0), ("a", "", 1, 20), ("a", "en", 1, 7)]
    assert rollup.commit("b2", batch(("revise", 1, "b", "en", "t", 9, 0), ("delete", 2, None, None, "t", None, 0), ("delete", 99, None, None, "t", None, 0), ("revise", 4, "b", "en", "t", 1, 0), ("insert", 5, "c", "c", "t", 5, 1), ("delete", 5, "c", "c", "t", None, 1)))
    assert totals() == [("", "en", 1, 0), ("b", "en", 2, 10)]
    assert rollup.commit("b3", one.limit(0)) and totals() == [("", "en", 1, 0), ("b", "en", 2, 10)]
    # a batch that broke off before its marker is overwritten
    batch(("insert", 8, "z", "z", "t", 3, 0)).select("doc_id", "source", "lang", "tokenizer", F.lit(1).cast("long").alias("docs"), F.lit(3).cast("long").alias("tokens")).write.parquet(rollup._path("ledger", "b4"))
    assert totals() == [("", "en", 1, 0), ("b", "en", 2, 10)] and rollup.commit("b4", batch(("insert", 9, "z", "z", "t", 4, 0))) and ("z", "z", 1, 4) in totals()


def test_rollups_keep_rows_without_ids_and_fold(spark):
    rollup = token_rollups.Rollup(spark, Scratch(spark, "t2").path("state"))
    schema = "op string, doc_id long, source string, lang string, tokenizer string, n_tokens long, seq int, part string"
    batch = lambda *rows: spark.createDataFrame([(*r, "clash") for r in rows], schema)
    totals = lambda: sorted((r["source"] or "", r["n_docs"], r["n_tokens"]) for r in rollup.totals().collect())
    assert rollup.commit("1", batch(*[("insert", None, "a", None, "t", 5, 0)] * 4, *[("insert", i, "b", None, "t", i, 0) for i in range(40)], ("delete", None, "a", None, "t", None, 0)))
    assert totals() == [("a", 4, 20), ("b", 40, 780)]
    rollup.compact()
    assert totals() == [("a", 4, 20), ("b", 40, 780)] and not rollup.commit("1", batch())
    assert rollup.commit("2", batch(("revise", 3, "c", None, "t", 100, 0), ("delete", 39, "b", None, "t", None, 0), ("revise", None, "a", None, "t", 1, 0)))
    assert totals() == [("a", 5, 21), ("b", 38, 738), ("c", 1, 100)]
    rollup.compact()
    assert totals() == [("a", 5, 21), ("b", 38, 738), ("c", 1, 100)] and rollup.committed() == ["1", "2"]
    # a second attempt that ended too doesn't count twice
    rollup._mark("commits", "2", "zzz")
    assert totals() == [("a", 5, 21), ("b", 38, 738), ("c", 1, 100)]


def test_targets_are_resolved(spark):
    cases = [
        ("/de/1", "http://bad.com/x/y?q#f", "http://bad.com/de/1"), ("//bad.com/de/1", "https://a.net/x", "https://bad.com/de/1"), ("?p=2&amp;q=3", "http://a.net/x/y?z", "http://a.net/x/y?p=2&q=3"),
        ("b", "http://a.net/x/y", "http://a.net/x/b"), ("../b/./c?d=../e", "http://a.net/x/y/z", "http://a.net/x/b/c?d=../e"), ("../../..", "http://a.net/x", "http://a.net/"), ("b", "http://a.net", "http://a.net/b"),
        ("http://c.d/?a=1&#38;b", "no base", "http://c.d/?a=1&b"), ("b", "no base", None), ("#top", "http://a.net/x", None), ("mailto:x@y", "http://a.net/x", None), ("go?u=http://z", "http://a.net/x/y", "http://a.net/x/go?u=http://z"), ("x/", "http://a.net/y/", "http://a.net/y/x/"),
    ]
    df = spark.createDataFrame(cases, "t string, b string, want string")
    for r in df.withColumn("got", url_aliases.resolved(F.col("t"), F.col("b"))).collect():
        assert r["got"] == r["want"], r
    pages = spark.createDataFrame([(1, "http://mirror.net/a", '<link rel=canonical href="//bad.com/de/1?x=1&amp;y=2">'), (2, "http://bad.com/fr/2", '<link rel="canonical" href="/de/2">'), (3, "http://bad.com/x" + "y" * 100_000, "")], "page_id long, url string, html string")
    got = {r["page_id"]: r["verdict"] for r in url_aliases.judge_urls(pages).collect()}
    assert got == {1: "block", 2: "allow", 3: "allow"}


def test_clashes_are_found_in_any_case(spark):
    d = spark.createDataFrame([(1, "a", "en", "s", "x")], "doc_id long, text string, lang string, source string, url string")
    for run, name in ((quality_rules.judge, "Kept"), (license_scan.scan, "Licenses"), (line_winnow.dedup_lines, "REMOVED"), (language_mix.identify_languages, "Held_Out"), (url_aliases.judge_urls, "Verdict")):
        with pytest.raises(ValueError):
            run(d.withColumn(name, F.lit(1)))


# --- licenses ------------------------------------------------------------------------------------------------------


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(0, 9), max_size=14), st.lists(st.integers(0, 9), max_size=14))
def test_alignment_matches_equal_words_in_order(a, b):
    pairs = license_scan.align(a, b)
    assert all(a[i] == b[j] for i, j in pairs) and all(p[0] < q[0] and p[1] < q[1] for p, q in zip(pairs, pairs[1:]))
    if sorted(a) == sorted(set(a)) and a == b:
        assert len(pairs) == len(a)


@given(st.lists(st.integers(0, 30), max_size=40))
def test_rising_is_a_longest_one(places):
    best = []
    for x in places:
        best.append(1 + max([b for b, y in zip(best, places) if y < x], default=0))
    got = [places[i] for i in license_scan.rising(places)]
    assert len(got) == max(best, default=0) and got == sorted(set(got))


def test_licenses(docs_of):
    mit = license_scan.TEMPLATES["mit-text"]
    texts = [None, "", prose(1, 20_000), f"{prose(3, 50)}\nReleased under the MIT License.\n{prose(4, 50)}", f"Licensed under CC BY-NC 4.0. {prose(5, 30)} ALL RIGHTS RESERVED", mit.replace("free of charge", "gratis"), f"{mit}\n{prose(6, 9)}\n{mit}", "the licence was released by the author of the work", prose(7, 30) + " Licensed under the Apache License, Version 2.0."]
    df = docs_of(texts)
    out = {r["doc_id"]: r for r in license_scan.scan(df).filter("doc_id is not null").collect()}
    names = lambda i: [x["license"] for x in out[i]["licenses"]]
    assert [names(i) for i in range(9)] == [[], [], [], ["mit"], ["cc-by-nc-4.0", "all-rights-reserved"], ["mit-text"], ["mit-text", "mit-text"], [], ["apache-2.0"]]
    hit = out[3]["licenses"][0]
    assert texts[3][hit["start"] : hit["end"]] == "Released under the MIT License" and hit["coverage"] == 1.0
    assert license_scan.scan(df).count() == df.count() and license_scan.scan(df.limit(0)).count() == 0


def test_edited_notices_are_found_whichever_words_went():
    """Of templates of ten words and more, any two words may be others (a fifth of them, drawn, for long ones) and words may come between."""
    scanner, rng = license_scan.Scanner(), random.Random(11)
    for name, template in license_scan.TEMPLATES.items():
        words = template.split()
        n = len(re.findall("[0-9a-z]+", template.lower()))
        if n < 10:
            continue
        edits = [(i, j) for i in range(len(words)) for j in range(i)]
        edits += [tuple(rng.sample(range(len(words)), n // 5 - 1)) for _ in range(100)]
        for gone in edits:
            left = [f"other{rng.randrange(99)}" if i in gone else w for i, w in enumerate(words)]
            covered = len(re.findall("[0-9a-z]+", " ".join(w for i, w in enumerate(words) if i not in gone).lower())) / n
            text = f"{prose('before', 15)} {' '.join(left)} {prose('after', 15)}"
            found = [x for x in scanner.scan(text.encode()) if x[0] == name]
            assert bool(found) == (covered >= 0.8), (name, gone)
            assert not found or abs(found[0][1] - covered) < 1e-9


def test_two_notices_side_by_side_are_two():
    scanner = license_scan.Scanner()
    for a in ("mit-text", "gpl-notice", "bsd", "isc"):
        both = scanner.scan(f"{license_scan.TEMPLATES[a]} {license_scan.TEMPLATES[a]} {prose('x', 9)} {license_scan.TEMPLATES['cc-by-4.0']}".encode())
        assert [x[0] for x in both] == [a, a, "cc-by-4.0"] and all(x[1] == 1.0 for x in both)
