"""Each operator against brute force on small rows: nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns."""

import base64
import collections
import gzip
import hashlib
import math
import random
import re
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from blocksolve.llm import chat, langid, mixing, nearest, neardup, ppm, quality, sentencepieces, substrings, warc
from blocksolve.llm.common import materialize
from blocksolve.llm.queries import piece_model

WORD = r"[^\x20\x09-\x0D]+"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def said(rng, n, vocabulary=400):
    return " ".join(f"{rng.choice('abcdefgh')}w{rng.randrange(vocabulary)}" for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(5)
    base = [said(rng, 200) for _ in range(6)]
    near = base[0].split()
    near[17] = "changed"
    out = [(i, t, "en", "s0", 1) for i, t in enumerate(base)]
    out += [(10, base[1], "en", "s1", 1), (11, " ".join(near), "de", "s1", 1), (12, None, None, None, None), (13, "", "en", "s2", 0), (14, " \n\t ", "en", "s2", 3)]
    out += [(15, base[2] + "\n" + base[3], "fr", "s0", 1), (16, "ünïcode wörter 中文 🙂", "de", "s3", 1), (17, said(rng, 30000), "en", "s0", 1), (17, base[4], "en", "s0", 1), (17, base[4], "en", "s0", 1)]
    out += [(None, base[5] + " tail", "en", "s0", 1), (18, "12 34 .. 56", "en", "s4", 1), (19, "x" * 40000, "en", "s4", 1)]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, DOCS)


def clashing(df, *names):
    return df.withColumns({n: F.lit("mine") for n in names})


# --- 1 ------------------------------------------------------------------------------------------


def test_lists_of_ids_with_nulls_are_made_from_arrays(monkeypatch):
    """No list becomes an arrow value by itself, a null among them or not."""
    import pyarrow as pa

    for values in ([[1, 2], None, [], [3]], [[1], [2]], [None], []):
        plain = pa.array(values, pa.list_(pa.int32()))
        with monkeypatch.context() as m:
            made = pa.array
            m.setattr(sentencepieces.pa, "array", lambda x, *how: made(x, *how) if not isinstance(x, list) or not any(isinstance(v, list) for v in x) else pytest.fail("a list"))
            assert sentencepieces._lists(values).to_pylist() == plain.to_pylist()


def test_pieces_equal_the_library_for_any_chunk_size(spark, docs):
    model = sentencepieces.Model(open(piece_model(), "rb").read())
    for size in (23, 400, 1 << 15):
        got = sentencepieces.decode(sentencepieces.encode(clashing(docs.where("doc_id IS NULL OR doc_id <> 17"), "ids", "_key1", "decoded"), piece_model(), size=size), piece_model()).collect()
        assert len(got) == 16
        for r in got:
            assert r["ids"] == (None if r["text"] is None else model.library.encode(r["text"]))
            assert r["decoded"] == r["text"]


def test_scan_on_strings_without_white_space():
    model = sentencepieces.Model(open(piece_model(), "rb").read())
    rng = random.Random(1)
    for _ in range(60):
        text = "".join(rng.choice("aeinthgosr é_▁中") for _ in range(rng.randrange(1, 150)))
        t = model.normalized(text)
        for size in (1, 7, 50):
            cuts = range(0, len(t), size)
            chunks = [
                sentencepieces.Chunk(model, t[max(0, a - model.longest) : min(len(t), a + size) + model.longest], a - max(0, a - model.longest), min(len(t), a + size) - a, a == 0, a + size >= len(t)) for a in cuts
            ]
            at = sentencepieces.states([c.matrix() for c in chunks])
            assert [i for c, x, y in zip(chunks, at[:-1], at[1:], strict=True) for i in c.ids(x, y)] == model.library.encode(text)


def test_products_are_associative():
    a, b, c = [(0, 1, 1.0), (0, 2, 3.0)], [(1, 5, 2.0), (2, 5, 1.0)], [(5, 6, 0.5)]
    left, right = sentencepieces.product(sentencepieces.product(a, b), c), sentencepieces.product(a, sentencepieces.product(b, c))
    assert left == right == [(0, 6, 4.5)]


# --- 2 ------------------------------------------------------------------------------------------


def test_snapshots_collapse(spark):
    turns = [(1, 0, "user", "hi"), (1, 1, "bot", "yo"), (2, 0, "user", "hi"), (2, 1, "bot", "yo"), (2, 2, "user", "bye"), (3, 0, "user", "hi"), (3, 1, "bot", "no"), (4, 0, "user", "hi"), (5, 0, None, None), (6, 0, None, None)]
    turns += [(7, 1, "bot", "yo"), (7, 0, "user", "hi"), (7, 2, "user", "bye"), (None, 0, "user", "lost"), (8, 0, "user", "hi"), (8, 0, "user", "hi")]
    df = clashing(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string"), "place", "a", "b", "n_turns", "rendered")
    got = {r["conv_id"]: (r["n_turns"], r["rendered"]) for r in chat.collapse_and_render(df).collect()}
    assert set(got) == {2, 3, 5, 8}
    assert got[2] == (3, "<|im_start|>user\nhi<|im_end|>\n<|im_start|>bot\nyo<|im_end|>\n<|im_start|>user\nbye<|im_end|>\n")
    assert got[5] == (1, "<|im_start|>\n<|im_end|>\n")
    assert chat.collapse_and_render(df.limit(0)).count() == 0


# --- 3 ------------------------------------------------------------------------------------------


def jaccard_classes(rows, n=5, t=0.8):
    sets = []
    for r in rows:
        w = re.findall(WORD, r[1] or "")
        sets.append({tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set())
    parent = list(range(len(rows)))

    def top(i):
        while parent[i] != i:
            i = parent[i]
        return i

    links = collections.Counter()
    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and len(sets[i] & sets[j]) >= t * len(sets[i] | sets[j]):
                links[i] += 1
                links[j] += 1
                parent[top(i)] = top(j)
    ids = collections.defaultdict(list)
    for i, r in enumerate(rows):
        ids[top(i)].append(r[0])
    least = {k: min((x for x in v if x is not None), default=None) for k, v in ids.items()}
    return sorted(((r[0], least[top(i)], links[i]) for i, r in enumerate(rows)), key=str)


def test_join_finds_every_link(spark, docs, rows):
    got = sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in neardup.join(clashing(docs, "k2", "node", "size")).collect()), key=str)
    assert got == jaccard_classes(rows)


def test_join_counts_links_in_large_groups_across_blocks(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BLOCK", 8)
    rng = random.Random(2)
    base = said(rng, 150).split()
    rows = []
    for i in range(60):
        w = list(base)
        for p in rng.sample(range(150), rng.randrange(0, 4)):
            w[p] = f"n{i}x{p}"
        rows.append((i, " ".join(w)))
    got = sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in neardup.join(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == jaccard_classes(rows)


def test_dedup_keeps_one_of_each_class(spark, docs):
    kept = neardup.dedup(clashing(docs, "node", "hub", "_key1"))
    ids = [r["doc_id"] for r in kept.collect()]
    assert 10 not in ids and 11 not in ids and {0, 1, 12, 13, 14, 18, 19} <= set(ids)
    assert neardup.dedup(docs.limit(0)).count() == 0
    assert neardup.join(docs.where("text IS NULL")).count() == 1
    twice = docs.where("doc_id = 12 OR doc_id = 13").union(docs.where("doc_id = 12"))
    assert neardup.dedup(twice).count() == 3  # rows without words are classes of their own


def test_prefix_depth_follows_recall():
    assert neardup.depth_for(0.8) == 5
    assert neardup.depth_for(0.99) == neardup.DEPTH
    assert neardup.depth_for(0.3) == 1
    d = neardup.depths(0.8, 0.999)
    assert list(d[1:4]) == [neardup.DEPTH + 1] * 3 and d[6] == neardup.depth_for(5 / 6) and d[7] == neardup.depth_for(6 / 7) and d[-1] == d[100] == 5


def test_signatures_are_sorted_tries():
    """Values that agree in the first d levels share the leading bits of their signatures."""
    rng = np.random.default_rng(1)
    a = rng.integers(0, 2**63, 400, dtype=np.uint64)
    b = np.concatenate([a[:380], rng.integers(0, 2**63, 20, dtype=np.uint64)])
    s = neardup.signatures(np.concatenate([a, b, a]), np.array([0, 400, 800, 1200]))
    assert (s[0] == s[2]).all() and (s[0] != s[1]).any()
    first = neardup.WIDTHS[0]
    assert ((s[0] >> np.uint64(64 - first)) == (s[1] >> np.uint64(64 - first))).sum() >= 12  # 0.905 of the tries agree in a level


def test_forest_recall_at_the_threshold(spark):
    """Pairs hardly above the threshold, and sets of few shingles, against brute force."""
    rng = random.Random(11)
    rows = []
    for i in range(300):
        w = said(rng, 104, 10**6).split()
        other = w[: 104 - 11 + i % 3] + said(rng, 11 - i % 3, 10**6).split()  # 100 shingles, about 89 shared
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(other))]
    for i in range(300):
        w = [rng.choice("ab") for _ in range(rng.randrange(1, 14))]
        rows.append((1000 + i, " ".join(w)))
    got = {r["doc_id"]: r["n_links"] for r in neardup.join(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()}
    want = {i: n for i, _, n in jaccard_classes(rows)}
    assert sum(want.values()) > 800
    assert all(got[i] <= want[i] for i in want) and sum(got.values()) >= 0.998 * sum(want.values())
    assert {i: n for i, n in got.items() if i >= 1000} == {i: n for i, n in want.items() if i >= 1000}


# --- 4 ------------------------------------------------------------------------------------------


def test_archives_round_trip(spark, tmp_path):
    big = "é" * 600
    rows = [(1, "http://a", big), (5, "http://b c\n", big), (3, None, big), (2, "u", "small"), (4, "u", "small"), (6, "u", None), (None, "u", big), (7, "u", "x" * 100000), (5, "http://b", big)]
    df = clashing(spark.createDataFrame(rows, "page_id long, url string, html string"), "payload", "digest", "refers_to")
    archives = warc.write_archives(warc.plan_revisits(df))
    got = warc.read_archives(archives)
    by = collections.defaultdict(list)
    for r in got.collect():
        assert r["status"] == "ok"
        by[r["page_id"]].append(r)
    for page, _, html in rows:
        data = (html or "").encode()
        for r in by[page]:
            assert (r["payload_bytes"], r["payload_digest"]) == (len(data), hashlib.sha1(data).hexdigest())
            want = ("revisit", 5) if data == big.encode() and page != 5 else ("response", None)
            assert (r["record_type"], r["refers_to"]) == want
            assert want[0] == "revisit" or bytes(r["payload"]) == data
    full = warc.resolve(got.where("page_id <> 5").union(got.where("page_id = 5").limit(1))).where("page_id = 1").first()
    assert bytes(full["payload"]) == big.encode()
    data = bytes(archives.first()["data"])
    assert gzip.decompress(data).startswith(b"WARC/1.1\r\n")
    (tmp_path / "a.warc.gz").write_bytes(data)
    assert warc.read_files(spark, str(tmp_path)).count() == archives.first()["records"]
    assert warc.read_archives(warc.write_archives(warc.plan_revisits(df.limit(0)))).count() == 0


def test_damaged_archives_say_so():
    good = warc._records(1, "u", b"data", None, "2024-01-01T00:00:00Z", 3)
    assert [r[-1] for r in warc._read(good + good[:-9], True)] == ["ok", "unreadable: truncated member"]
    head = [("WARC-Type", "response"), ("WARC-Record-ID", "<urn:page:1>"), ("WARC-Payload-Digest", "sha1:" + base64.b32encode(b"\0" * 20).decode())]
    assert next(warc._read(warc._member(head, b"HTTP/1.1 200 OK\r\n\r\nx", 3), True))[-1] == "payload digest differs"
    assert list(warc.members(good, 1)) == [gzip.decompress(good)]


# --- 5 ------------------------------------------------------------------------------------------


def test_mixing_reaches_its_weights(spark):
    rows = [(i, "x" * 100, "en", "a" if i % 3 else "b", 100) for i in range(3000)]
    df = clashing(spark.createDataFrame(rows, DOCS), "rate", "copy_no", "cdf")
    got = {r["source"]: r["n"] for r in mixing.mix(df, {"a": 1.0, "b": 1.0}).groupBy("source").agg(F.count("*").alias("n")).collect()}
    assert abs(got["a"] - 1500) < 150 and abs(got["b"] - 1500) < 150
    again = mixing.mix(df, {"a": 1.0, "b": 1.0})
    assert sorted((r["doc_id"], r["copy_no"]) for r in again.collect()) == sorted((r["doc_id"], r["copy_no"]) for r in mixing.mix(df.repartition(3), {"a": 1.0, "b": 1.0}).collect())


def test_mixing_draws_a_poisson_law(spark):
    for rate in (0.4, 3.0, 37.5):
        law = mixing.with_cdf(spark.range(4000).select(F.col("id").cast("string").alias("source"), F.lit(rate).alias("rate")))
        n = np.array([r[0] for r in law.select(mixing.copies(F.col("parts"), F.col("cdf"), F.col("source"), 3)).collect()])
        assert abs(n.mean() - rate) < 5 * math.sqrt(rate / 4000) and abs(n.var() - rate) < 0.15 * rate + 0.05


def test_mixing_edges(spark, docs):
    out = mixing.mix(docs)
    assert out.columns == [*docs.columns, "copy_no"]
    assert mixing.mix(docs.limit(0)).count() == 0
    assert mixing.mix(docs.where("source = 's0'"), {"absent": 1.0}).count() > 0  # no target at all: every rate is 1


# --- 6 ------------------------------------------------------------------------------------------


def removed(rows, k=35):
    count, words = collections.Counter(), []
    for r in rows:
        w = re.findall(WORD, r[1] or "")
        words.append(w)
        count.update(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
    out = []
    for r, w in zip(rows, words, strict=True):
        gone = [False] * len(w)
        for i in range(len(w) - k + 1):
            if count[tuple(w[i : i + k])] > 1:
                gone[i : i + k] = [True] * k
        kept = [x for x, g in zip(w, gone, strict=True) if not g]
        out.append((r[0], len(w), sum(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest(), kept))
    return sorted(out, key=str)


def test_substrings_equal_brute_force(spark, docs, rows):
    extra = [(30, " ".join(["ab"] * 100)), (31, " ".join("a b c".split() * 30)), (32, "z " + " ".join(f"u{i}" for i in range(60))), (33, " ".join(f"u{i}" for i in range(10, 70)) + "\n")]
    rows = [r[:2] for r in rows] + extra
    df = clashing(spark.createDataFrame(rows, "doc_id long, text string"), "kept", "spans", "_key2", "m")
    got = sorted(((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"], re.findall(WORD, r["kept"] or "")) for r in substrings.cut(df).collect()), key=str)
    assert got == removed(rows)
    assert substrings.cut(df.limit(0)).count() == 0


def test_repeated_rows_have_their_spans_once(spark):
    x = said(random.Random(3), 300)
    df = substrings.keyed(spark.createDataFrame([(7, x)] * 50, "doc_id long, text string"), "doc_id", "text")
    spans = [r["spans"] for r in substrings.repeated_spans(df).collect()]
    assert len(spans) == 1 and [s["code"] for s in spans[0]] == [300]  # one path, words 0 to 300


def test_paths_end_where_the_graph_branches(spark):
    """A shared passage of 200 words with a detour in one text: two paths in the texts that lack it, verified by their words."""
    rng = random.Random(9)
    shared, tail = said(rng, 200, 10**6).split(), said(rng, 90, 10**6).split()
    rows = [(1, " ".join(said(rng, 60, 10**6).split() + shared + tail)), (2, " ".join(shared + said(rng, 70, 10**6).split())), (3, " ".join(said(rng, 50, 10**6).split() + shared[100:] + tail))]
    df = substrings.keyed(spark.createDataFrame(rows, "doc_id long, text string"), "doc_id", "text")
    spans = {r["_key1"]: sorted((s["code"] >> 32, s["code"] & 0xFFFFFFFF) for s in r["spans"]) for r in substrings.repeated_spans(df).collect()}
    assert max(b for _, b in spans[2]) == 200 and min(a for a, _ in spans[2]) == 0
    assert max(b for _, b in spans[1]) == 350 and min(a for a, _ in spans[1]) == 60
    verified = [s for r in substrings.repeated_spans(df).collect() for s in r["spans"] if (s["d1"], s["d2"]) != (0, 0)]
    assert verified and max((s["code"] & 0xFFFFFFFF) - (s["code"] >> 32) for s in verified) > 60  # compacted beyond one piece


def test_spans_of_other_words_stay():
    """A path whose words differ from those at the source coordinate removes nothing."""
    words = " ".join(f"w{i}" for i in range(60))
    span = lambda d: pa.array([[{"code": (2 << 32) + 50, "d1": d, "d2": 5}]], pa.list_(pa.struct([("code", pa.int64()), ("d1", pa.int64()), ("d2", pa.int64())])))
    assert substrings.without(pa.array([words]), span(7))[2].to_pylist() == [0]
    w = substrings.tk.Words(pa.array([words]))
    d1, d2 = np.frombuffer(substrings._Packed(w).digest(2, 50), np.int64)
    good = pa.array([[{"code": (2 << 32) + 50, "d1": int(d1), "d2": int(d2)}]], span(7).type)
    assert substrings.without(pa.array([words]), good)[2].to_pylist() == [48]
    assert substrings._Packed(w).digest(2, 4) == hashlib.sha1(b"w2 w3").digest()[:16]


def test_substrings_random(spark):
    rng = random.Random(9)
    passages = [[f"p{i}_{j}" for j in range(rng.randrange(30, 60))] for i in range(4)]
    rows = []
    for i in range(40):
        w = [f"q{i}_{j}" for j in range(rng.randrange(0, 30))]
        for _ in range(rng.randrange(0, 3)):
            p = rng.choice(passages)
            a = rng.randrange(0, 8)
            w += p[a : len(p) - rng.randrange(0, 8)] + [f"r{rng.randrange(10**6)}"]
        rows.append((i, rng.choice([" ", "\n", "  "]).join(w)))
    got = sorted(((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.cut(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == [r[:4] for r in removed(rows)]


# --- 7 ------------------------------------------------------------------------------------------


def test_top_k_is_exact(spark, monkeypatch):
    monkeypatch.setattr(nearest, "BLOCK", 16)
    monkeypatch.setattr(nearest, "CHUNK", 4)
    monkeypatch.setattr(nearest, "CELLS", 64)
    rng = np.random.default_rng(3)
    v = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(400)] + [(400 + i, [0.5] * 8) for i in range(40)]
    odd = [(900, None), (901, [1.0, None] + [0.0] * 6), (902, [float("nan")] * 8), (903, [float("inf")] * 8), (None, [1.0] * 8), (904, []), (905, [2.0]), (3, v[3][1])]
    df = clashing(spark.createDataFrame(v + odd, "vec_id long, embedding array<double>"), "id", "v", "pivot", "far")
    got = nearest.top_k(df, df.where("vec_id % 20 = 0"), k=7, block=16).collect()
    rows = [(i, [math.floor(64 * x) for x in e]) for i, e in v + [odd[5], odd[6], odd[7]]]
    want = []
    for q, qv in rows:
        if q % 20 == 0:
            s = sorted(((-sum(a * b for a, b in zip(qv, cv, strict=False)), c) for c, cv in rows if c != q))[:7]
            want += [(q, n + 1, c, -x) for n, (x, c) in enumerate(s)]
    assert sorted(map(tuple, got)) == sorted(want)
    assert nearest.top_k(df.limit(0), df.limit(0)).count() == 0
    few = df.where("vec_id < 3")
    assert nearest.top_k(few, few.where("vec_id = 0"), k=20).count() == 2


def test_top_k_reads_few_annuli_of_clustered_vectors(spark):
    rng = np.random.default_rng(8)
    centres = rng.normal(size=(40, 16)) * 10
    v = [(i, [float(x) for x in centres[i % 40] / np.linalg.norm(centres[i % 40]) + rng.normal(size=16) * 0.01]) for i in range(4000)]
    df = spark.createDataFrame(v, "vec_id long, embedding array<double>")
    found, cost = nearest.search(df, df.where("vec_id % 100 = 0"), k=5, block=50)
    x = np.array([[math.floor(64 * e) for e in row] for _, row in v])
    for r in range(0, 4000, 400):
        s = x @ x[r]
        want = sorted((-int(s[j]), j) for j in range(4000) if j != r)[:5]
        assert [(-m["score"], m["vec_id"]) for m in found.where(F.col("query_id") == r).orderBy("rank").collect()] == want
    assert cost["pairs"] == 40 * 4000 and cost["scored"] < 0.2 * cost["pairs"]


def test_scores_beyond_64_bits_are_held(spark):
    df = spark.createDataFrame([(0, [1e15, 1e15]), (1, [1e15, 1e15]), (2, [-1e15, 0.0])], "vec_id long, embedding array<double>")
    got = nearest.top_k(df, df.where("vec_id = 0")).orderBy("rank").collect()
    assert [(r["vec_id"], r["score"]) for r in got] == [(1, 2**63 - 1), (2, -(2**63))]


# --- 8 ------------------------------------------------------------------------------------------


def counts(text):
    text = text or ""
    w = re.findall(WORD, text)
    tri = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = {i + j for i in range(len(w) - 2) if tri[tuple(w[i : i + 3])] > 1 for j in range(3)}
    lines = [x for x in text.split("\n") if re.search(WORD, x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(hit)


def test_quality_counts(spark, docs, rows):
    more = [(40, "a b c a b c d", "en", "s", 1), (41, "x\ny\nx\n \n \nx", "en", "s", 1), (42, "#a $b <c> a|b " * 3, "en", "s", 1)]
    df = clashing(docs.union(spark.createDataFrame(more, DOCS)), "n_words", "stratum", "w")
    got = sorted(((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in quality.measures(df).collect()), key=str)
    assert got == sorted(((r[0], *counts(r[1])) for r in rows + more), key=str)


def ladder_brute(shares, alpha, delta):
    """source -> cutoffs of the three rules, from (source, symbol, line, repeat) of the labelled good documents."""
    grid, sources = sorted(quality.GRID, reverse=True), {x[0] for x in shares}
    least = math.log(delta / (len(sources) + 1)) / math.log(1 - alpha)
    size = collections.Counter(x[0] for x in shares)
    families = {x: x if size[x] >= least else "pool of small ones" for x in sources}
    out = {}
    for fam in set(families.values()):
        mine = [x[1:] for x in shares if families[x[0]] == fam]
        cuts, kept = [None] * 3, [None] * 3
        for step in range(3 * len(grid)):
            cuts[step % 3] = grid[step // 3]
            k = sum(any(c is not None and x > c for x, c in zip(m, cuts, strict=True)) for m in mine)
            tail = sum(math.comb(len(mine), i) * alpha**i * (1 - alpha) ** (len(mine) - i) for i in range(k + 1))
            if tail > delta / len(set(families.values())):
                break
            kept = list(cuts)
        out |= {x: kept for x in sources if families[x] == fam}
    return out


def test_thresholds_limit_false_rejections(spark):
    rng = random.Random(4)
    source = lambda i: None if i % 10 == 0 else "big" if i % 10 < 7 else f"small{i % 10}"
    rows = [(i, said(rng, 80) + " " + "# " * (i % 60) + "\nagain" * (i % 7 == 0) * 2 + "\nagain" * (i % 50 == 0), "en", source(i), 1) for i in range(900)]
    df = spark.createDataFrame(rows + [(5000, said(rng, 80) + " #" * 70, "en", "unlabelled", 1), (None, None, None, None, None)], DOCS)
    good = {i for i in range(900) if i % 60 < 25}
    labels = spark.createDataFrame([(i, int(i in good)) for i in range(900)] + [(None, 1), (1, None)], "doc_id long, quality int")
    m = quality.shares(materialize(quality.measures(df), "m"))
    held = [(r["stratum"], r["symbol_share"], r["dup_line_share"], r["repeat_share"]) for r in m.where(~quality.base_failed()).collect() if r["doc_id"] in good]
    want = ladder_brute(held, 0.05, 0.05)
    told = {r["stratum"]: r for r in quality.thresholds(m, labels, alpha=0.05).collect()}
    assert {k: [r[f"cut_{x}"] for x in quality.RULES] for k, r in told.items()} == want
    assert not told["big"]["pooled"] and told["small7"]["pooled"] and told["big"]["cut_symbol_share"] is not None and told["small7"]["cut_symbol_share"] is not None
    judged = quality.judge(df, labels, alpha=0.05)
    lost = [r for r in judged.where("size(rejected_by) > 0 AND NOT base_failed").collect()]
    assert len(lost) > 200 and not any(r["stratum"] == "unlabelled" for r in lost)
    assert sum(r["doc_id"] in good for r in lost) <= 0.05 * len(held)
    assert quality.judge(df, labels.limit(0)).where("size(rejected_by) > 0").count() == 0
    assert quality.judge(df.limit(0), labels).count() == 0


def test_cutoffs_are_certified_on_the_tables(spark):
    """The given labels suffice for every source, in one stratum or their own, and the rules reject documents that the base rule passes."""
    d = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{d}/{n}.parquet") for n in ("documents", "labels"))
    m = quality.shares(materialize(quality.measures(docs), "m"))
    told = quality.thresholds(m, labels).collect()
    assert len(told) == 20 and all(r["cut_symbol_share"] is not None and r["rejected"] <= 0.02 * r["n"] for r in told)
    assert quality.judge(docs, labels).where("NOT kept AND NOT base_failed").count() > 10


def test_binomial_tail(spark):
    for n, k, p in ((50, 0, 0.02), (500, 3, 0.02), (2000, 20, 0.02), (60000, 900, 0.02), (10, 9, 0.02)):
        got = spark.range(1).select(F.lit(k).cast("long").alias("k"), F.lit(n).cast("long").alias("n")).select(quality.log_binomial_cdf("k", "n", p)).first()[0]
        logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
        top = max(logs)
        want = top + math.log(sum(math.exp(x - top) for x in logs))
        assert got == pytest.approx(0.0 if k > n * p else want, rel=1e-6, abs=1e-9)


# --- 9 ------------------------------------------------------------------------------------------


def test_languages(spark, docs, rows):
    rng = random.Random(6)
    make = {"aa": ["tho", "ing", "ers"], "bb": ["ung", "sch", "ein"], "ü": ["ção", "ões", "não"]}
    learn = spark.createDataFrame([("".join(rng.choice(make[k]) + rng.choice(["", " "]) for _ in range(200)), k) for k in make for _ in range(20)] + [(None, "aa"), ("text", None), ("", "bb")], "text string, lang string")
    model = langid.train(learn)
    test = spark.createDataFrame([(i, k, "".join(rng.choice(make[k]) + rng.choice(["", " "]) for _ in range(60))) for i, k in enumerate(list(make) * 5)], "i int, want string, text string")
    got = langid.predict(clashing(test, "score", "lang_pred"), model, ["i", "want", "text"]).collect()
    assert all(r["want"] == r["lang_pred"] and 0.5 < r["score"] <= 1 for r in got)
    edge = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in langid.predict(docs, model, docs.columns).collect()}
    assert edge[12] == edge[13] == edge[14] == edge[18] == ("und", 0.0)
    assert edge[16][0] in make
    none = langid.train(learn.limit(0))
    assert {r["lang_pred"] for r in langid.predict(docs, none, ["doc_id"]).collect()} == {"und"}
    assert langid.predict(docs.limit(0), model, ["doc_id"]).count() == 0


def language_brute(learn, text, share, floor):
    """(lang, score) by sets of n-grams in plain Python."""

    def runs(x):
        low = [b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in x.encode()]
        return [g for g in (tuple(low[i : i + 4]) for i in range(len(low) - 3)) if g != (32,) * 4]

    n = collections.defaultdict(collections.Counter)
    for x, lang in learn:
        if x is not None and lang is not None:
            n[lang].update(runs(x))
    total = {k: sum(c.values()) for k, c in n.items()}
    langs = sorted((k for k in n if total[k]), key=lambda k: (-total[k], k))
    rate = {k: {g: c / total[k] for g, c in n[k].items() if c / total[k] >= floor} for k in langs}
    top = collections.Counter()
    for k in langs:
        for g, r in rate[k].items():
            top[g] = max(top[g], r)
    if not any(c.isalpha() for c in text or ""):
        return "und", 0.0
    mine = runs(text)
    score = {k: sum(rate[k].get(g, -1) >= share * top[g] for g in mine) / max(1, len(mine)) for k in langs}
    best = max(langs, key=lambda k: score[k])
    return best, score[best]


def test_languages_equal_brute_force(spark, tables):
    """The tables' texts, learned and held out, against n-gram sets: scores up to the filter's false positives."""
    all_rows = [(r["doc_id"], r["text"], r["lang"]) for r in materialize(spark.read.parquet(f"{tables}/documents.parquet"), "d").collect()] + [(-1, "Ünï", "en"), (-2, None, "de"), (-3, "ab 12", None)]
    learn = [(x, k) for i, x, k in all_rows if i % 3]
    model = langid.train(spark.createDataFrame(learn, "text string, lang string"))
    got = {r["i"]: (r["lang_pred"], r["score"]) for r in langid.predict(spark.createDataFrame(all_rows, "i long, text string, lang string"), model, ["i"]).collect()}
    same = 0
    for i, x, _ in all_rows[::3] + all_rows[-3:]:
        lang, score = language_brute(learn, x, 0.3, 2e-6)
        assert got[i][1] == pytest.approx(score, abs=0.02)
        same += got[i][0] == lang
    assert same >= len(all_rows[::3])


def test_more_than_64_languages(spark):
    learn = spark.createDataFrame([(f"{chr(97 + i // 26)}{chr(97 + i % 26)}zq " * 30, f"l{i:02d}") for i in range(70)], "text string, lang string")
    model = langid.train(learn)
    assert model.bits.shape[1] == 2
    got = langid.predict(learn, model, ["text", "lang"]).where("lang <> lang_pred").count()
    assert got == 0


# --- 10 -----------------------------------------------------------------------------------------


def ppm_brute(learn, text, order):
    trie = {}
    for t in learn:
        d = bytes([255] * order) + (t or "").encode().lower() + b"\xff"
        for i in range(order, len(d)):
            for k in range(order + 1):
                m = trie.setdefault(d[i - k : i], {})
                m[d[i]] = m.get(d[i], 0) + 1
    d, total = bytes([255] * order) + (text or "").encode().lower() + b"\xff", 0.0
    for i in range(order, len(d)):
        out = set()
        for k in range(order, -1, -1):
            seen = trie.get(d[i - k : i])
            if not seen:
                continue
            live = {x: n for x, n in seen.items() if x not in out}
            whole = sum(live.values())
            if d[i] in live:
                total += math.log10((live[d[i]] - 0.5) / whole)
                break
            if live:
                total += math.log10(len(live) / 2 / whole)
            out |= seen.keys()
        else:
            total -= math.log10(256 - len(out))
    return total


@pytest.mark.parametrize("head", [0, 5, 1 << 18])
def test_scores_equal_brute_force(spark, head):
    learn = ["the cat sat on the mat", "The Cat", "", None, "a cat is a cat", "ünï"]
    test = ["the cat", "THE dog sat", "", None, "ünï x", "cat " * 50]
    order = 3
    model = ppm.train(spark.createDataFrame([(t,) for t in learn], "text string"), order=order)
    df = clashing(spark.createDataFrame(list(enumerate(test)), "i int, text string"), "score", "tail", "k")
    got = {r["i"]: r for r in ppm.score(df, model, ["i"], head=head).collect()}
    tokens = lambda t: [*re.findall(WORD, (t or "").translate({i: i + 32 for i in range(65, 91)})), None]
    c = collections.Counter(w for t in learn for w in tokens(t))
    for i, t in enumerate(test):
        w = tokens(t)
        assert (got[i]["n_tokens"], got[i]["n_known"]) == (len(w), sum(c[x] > 0 for x in w))
        assert got[i]["base_score"] == pytest.approx(sum(math.log10((c[x] + 1) / (sum(c.values()) + len(c) + 1)) for x in w))
        assert got[i]["score"] == pytest.approx(ppm_brute(learn, t, order), rel=1e-5)


@pytest.mark.parametrize("order, nodes", [(1, 4), (3, 0), (5, 8)])
def test_scores_do_not_depend_on_the_broadcast_grams(spark, monkeypatch, order, nodes):
    monkeypatch.setattr(ppm, "CHUNK", 16, raising=False)
    learn = ["the cat sat on the mat"] * 9 + ["The Cat", "", None, "ein Häuschen am Fluß", "中文 text 中文", "zzzzzzzz"]
    test = ["the cat", "THE dog sat", "", None, "ein Fluß", "中文中文", "q" * 400, "zz 🙂"]
    model = ppm.train(spark.createDataFrame([(t,) for t in learn], "text string"), order=order, nodes=nodes)
    df = clashing(spark.createDataFrame(list(enumerate(test)), "i int, text string"), "score", "head_score")
    got = {r["i"]: r["score"] for r in ppm.score(df, model, ["i"]).collect()}
    assert got == {i: pytest.approx(ppm_brute(learn, t, order), rel=1e-5) for i, t in enumerate(test)}


def test_heads_hold_whole_bands(spark):
    df = spark.range(1, 1001).select(F.col("id").alias("code"), F.col("id").alias("n"))
    for most in (0, 1, 50, 999, 1000, 5000):
        got = [r["n"] for r in ppm.heads(df, most).collect()]
        assert len(got) <= most and (most < 1000 or len(got) == 1000) and (not got or min(got) > 1000 - len(got))
    assert len(ppm.heads(df, 200).collect()) > 120


def test_nothing_learned_is_uniform(spark):
    empty = spark.createDataFrame([], "text string")
    model = ppm.train(empty)
    got = ppm.score(spark.createDataFrame([("ab",), (None,)], "text string"), model, ["text"]).collect()
    assert sorted(r["score"] for r in got) == pytest.approx(sorted([-3 * math.log10(256), -math.log10(256)]))
    assert ppm.score(empty, model, ["text"]).count() == 0


def test_adaptive_code_learns_as_it_goes():
    assert ppm.adaptive("abababababababab") > 2 * ppm.adaptive("abababab") + 2
    assert ppm.adaptive(None) == ppm.adaptive("") == pytest.approx(-math.log10(256))


def test_ppm_counting_holds_little(spark):
    class Learn:
        def mapInArrow(self, f, schema):
            self.f = f
            return self

        def select(self, *_):
            return self

        groupBy = agg = select

    rng = np.random.default_rng(5)
    letters = np.frombuffer(b"abcdefghijklmnopqrstuvw ", np.uint8)
    texts = [bytes(letters[rng.integers(0, 24, 5000)]).decode() for _ in range(1000)]
    learn = ppm.count(Learn())
    tracemalloc.start()
    total = [0, 0]
    for batch in learn.f(iter([pa.RecordBatch.from_pydict({"text": pa.array(texts)})])):
        for kind in (ppm.GRAM, ppm.WORD):
            total[kind] += batch["n"].to_numpy()[batch["kind"].to_numpy() == kind].sum()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert total == [5001 * 1000, sum(len(t.split()) + 1 for t in texts)]
    assert peak < 200 << 20, peak >> 20
