"""The pipeline against plain Python, stage by stage, on the smallest tables."""

import collections
import hashlib
import math
import re

import corpus_pipeline
from blocksolve.llm import sentencepieces
from blocksolve.llm.common import materialize, read
from blocksolve.llm.queries import piece_model

WORD = r"[^\x20\x09-\x0D]+"


def classes(texts, n=5, t=0.8):
    """The least id of each class of linked texts."""
    sets = {}
    for i, x in texts.items():
        w = re.findall(WORD, x)
        sets[i] = {tuple(w[j : j + n]) for j in range(max(1, len(w) - n + 1))} if w else set()
    top = {i: i for i in texts}

    def find(i):
        while top[i] != i:
            i = top[i]
        return i

    owners = collections.defaultdict(list)
    for i in sorted(sets):
        for g in sets[i]:
            owners[g].append(i)
    for a, b in {(v[0], x) for v in owners.values() for x in v[1:]} | {(x, y) for v in owners.values() if len(v) < 40 for x in v for y in v if x < y}:
        if len(sets[a] & sets[b]) >= t * len(sets[a] | sets[b]):
            a, b = find(a), find(b)
            top[max(a, b)] = min(a, b)
    return {i: find(i) for i in texts}


def test_run_equals_plain_python(spark, tables):
    docs, stages = read(spark, tables, "documents"), dict(corpus_pipeline.STAGES)
    columns = docs.columns
    text = {r["doc_id"]: r["text"] for r in docs.collect()}

    one = materialize(stages["language_id"](spark, docs, tables), "t1")
    assert one.columns == columns
    kept = {r["doc_id"] for r in one.collect()}
    assert {i for i, x in text.items() if not any(c.isalpha() for c in x or "")}.isdisjoint(kept) and len(kept) >= 0.97 * len(text)

    two = materialize(stages["ngram_jaccard"](spark, one, tables), "t2")
    first = classes({i: text[i] for i in kept})
    left = sorted(i for i in kept if first[i] == i)
    assert two.columns == columns and sorted(r["doc_id"] for r in two.collect()) == left

    three = materialize(stages["substring_dedup"](spark, two, tables), "t3")
    count = collections.Counter(tuple(w[i : i + 35]) for w in (re.findall(WORD, text[d]) for d in left) for i in range(len(w) - 34))
    want = {}
    for d in left:
        w = re.findall(WORD, text[d])
        gone = {i + j for i in range(len(w) - 34) if count[tuple(w[i : i + 35])] > 1 for j in range(35)}
        want[d] = [x for i, x in enumerate(w) if i not in gone]
    rows = {r["doc_id"]: r for r in three.collect()}
    assert three.columns == columns and {d: re.findall(WORD, r["text"]) for d, r in rows.items()} == want

    four = materialize(stages["source_mixing"](spark, three, tables), "t4")
    size = collections.Counter()
    for r in rows.values():
        size[r["source"]] += len(r["text"])
    share = {s: n**0.7 for s, n in size.items()}
    copies = collections.Counter()
    for r in rows.values():
        s = r["source"]
        rate = share[s] / sum(share.values()) * sum(size.values()) / size[s]
        parts = max(1, math.ceil(rate / 8))
        for j in range(1, parts + 1):
            u = (int(hashlib.md5(f"17|{r['doc_id']}|{j}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52
            cdf, p, k = math.exp(-rate / parts), math.exp(-rate / parts), 0
            while cdf < u:
                k += 1
                p *= rate / parts / k
                cdf += p
            copies[r["doc_id"]] += k
    got = collections.Counter(r["doc_id"] for r in four.collect())
    assert four.columns == columns and got == +copies

    five = stages["sentencepiece"](spark, four, tables).collect()
    library = sentencepieces.Model(open(piece_model(), "rb").read()).library
    assert collections.Counter(r["doc_id"] for r in five) == got
    assert all(r["ids"] == library.encode(rows[r["doc_id"]]["text"]) for r in five)
    assert corpus_pipeline.run(spark, tables).count() == len(five)


def test_language_id_keeps_texts_too_short_for_an_ngram(spark):
    texts = ["the cat sat on the mat " * 9, "Re.", "A.", "é", "12.", "", None, "Zug fährt nach Haus " * 9]
    docs = spark.createDataFrame([(i, t, "de" if i == 7 else "en") for i, t in enumerate(texts)], "doc_id long, text string, lang string")
    kept = {r["doc_id"] for r in dict(corpus_pipeline.STAGES)["language_id"](spark, docs, "").collect()}
    assert kept == {0, 1, 2, 3, 7}


def test_odd_rows_pass_through(spark, tmp_path):
    """Nulls in every column, empty and very long texts, repeated rows and ids, and extra columns named like what stages add."""
    rng = __import__("random").Random(5)
    said = lambda n: " ".join(rng.choice(("the", "cat", "sat", "house", "river", "garden")) + str(rng.randrange(9999)) for _ in range(n))
    one, giant = said(80), said(60000)
    rows = [(1, one, "en", "a", 1), (2, one, "en", "a", 1), (2, one, "en", "a", 1), (3, None, "en", "a", 1), (4, "", None, None, None), (None, said(60), "en", "b", 1), (None, None, None, None, None)]
    rows += [(5, giant, "en", "b", 1), (6, said(70), None, "b", None), (7, said(70), "en", None, 1), (8, "12 34", "en", "a", 1)]
    more = {c: "mine" for c in ("node", "spans", "rate", "ids", "copy_no", "lang_pred", "kept", "__mix_place")}
    docs = spark.createDataFrame([(*r, *more.values()) for r in rows], ", ".join(["doc_id long, text string, lang string, source string, n_chars long", *(f"{c} string" for c in more)]))
    docs.write.parquet(str(tmp_path / "some/documents.parquet"))
    got = [r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path / "some")).collect()]
    assert set(got) <= {1, None, 5, 6, 7} and len(set(got)) >= 3
    at = docs
    for name, stage in corpus_pipeline.STAGES[:3]:
        at = materialize(stage(spark, at, ""), name)
        assert at.columns == [c for c in docs.columns if c in at.columns] and {"doc_id", "text", "lang", "source", "n_chars"} <= set(at.columns)
    assert sorted((r["doc_id"] for r in at.collect()), key=str) == [1, 5, 6, 7, None]
    docs.limit(0).write.parquet(str(tmp_path / "none/documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path / "none")).count() == 0
