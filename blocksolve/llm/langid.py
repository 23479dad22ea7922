"""Language identification by n-gram filters that hold a bit per language.

Training counts n-grams of ``N`` bytes of the lower-cased text (bytes that are no letter become
spaces) per language, over all learning rows. A language holds an n-gram if its rate there is at
least ``floor`` (so a language holds 1/floor n-grams at most) and at least ``share`` of the
n-gram's highest rate in any language. The filter is bit-sliced: slot s holds one bit for every
language, and an n-gram sets its languages' bits in ``HASHES`` slots; the AND of those slots is
the set of all languages that hold it, in one lookup. It has ``SLOTS`` slots whatever the input, so
what is collected and broadcast is bounded. Per document, set bits are counted for each language, the share
of hits is corrected for the filter's false positives, and the highest wins (ties: the more frequent
language, then the lesser name).

Defined results: a null text, or one without a letter, is ``und`` with score 0. A text without a
known n-gram gets the most frequent language with score 0. Rows with null lang teach nothing. If
nothing is learned, every text is ``und``. Extra columns pass through ``predict`` if asked for; one
named like a result is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksolve.llm import textkernel as tk
from blocksolve.llm.common import drop_table, materialize, without_columns

N, HASHES, SLOTS = 4, 3, 1 << 21
UNKNOWN = "und"
_TO = np.full(256, 32, np.uint8)
_TO[97:123] = np.arange(97, 123)
_TO[65:91] = np.arange(97, 123)
_TO[128:] = np.arange(128, 256)


def grams(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes of the n-grams of all rows, their rows' bounds, and per row whether it has an ASCII letter."""
    data, bounds = tk.text_bytes(column)
    low = _TO[data]
    n = max(0, len(low) - N + 1)
    code = np.zeros(n, np.uint32)
    for i in range(N):
        code = (code << np.uint32(8)) | low[i : i + n]
    ok = code != 0x20202020
    at = np.arange(n)
    row = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    if n:
        ok &= row[:n] == row[N - 1 :]
    keep = at[ok]
    letters = np.concatenate([[0], np.cumsum((low >= 97) & (low <= 122))])
    return code[keep], np.searchsorted(keep, bounds), (letters[bounds[1:]] - letters[bounds[:-1]]) > 0


def slots(code: np.ndarray, slots: int = SLOTS) -> Iterator[np.ndarray]:
    h = tk.mix(code.astype(np.uint64) + np.uint64(0x51ED27))
    for i in range(HASHES):
        yield (h >> np.uint64(21 * i)).astype(np.int64) & (slots - 1)


@dataclass
class Filter:
    langs: list[str]  # by falling frequency
    bits: np.ndarray  # slots x words of 64 languages

    def false_rate(self) -> np.ndarray:
        return np.array([(self.bits[:, i // 64] >> np.uint64(i % 64) & np.uint64(1)).mean() ** HASHES for i in range(len(self.langs))])


def count(learn: DataFrame, text: str, lang: str) -> DataFrame:
    """lang, code, n over all rows."""

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {}
        size = 0

        def out() -> Iterator[pa.RecordBatch]:
            for name, parts in held.items():
                code, n = merged(parts)
                yield pa.RecordBatch.from_pydict({"lang": pa.array([name] * len(code), pa.string()), "code": pa.array(code.astype(np.int64)), "n": pa.array(n)})
            held.clear()

        for batch in batches:
            texts, names = batch.column(0), batch.column(1).to_pylist()
            for lo, hi in tk.pieces(texts):
                code, at, _ = grams(texts.slice(lo, hi - lo))
                row = np.repeat(np.arange(hi - lo), np.diff(at))
                ids = {x: i for i, x in enumerate(dict.fromkeys(names[lo:hi]))}
                of = np.array([ids[x] for x in names[lo:hi]])[row]
                for name, i in ids.items():
                    u, n = np.unique(code[of == i], return_counts=True)
                    held.setdefault(name, []).append((u, n))
                    size += len(u)
            if size > 1 << 22:
                for name in held:
                    held[name] = [merged(held[name])]
                size = sum(len(p[0][0]) for p in held.values())
                if size > 1 << 21:
                    yield from out()
                    size = 0
        yield from out()

    return (
        learn.where(F.col(text).isNotNull() & F.col(lang).isNotNull())
        .select(text, lang)
        .mapInArrow(counts, "lang string, code long, n long")
        .groupBy("lang", "code")
        .agg(F.sum("n").alias("n"))
    )


def merged(parts: list) -> tuple[np.ndarray, np.ndarray]:
    code, n = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
    u, inv = np.unique(code, return_inverse=True)
    return u, np.bincount(inv, n, len(u)).astype(np.int64)


def train(learn: DataFrame, text: str = "text", lang: str = "lang", share: float = 0.3, floor: float = 2e-6) -> Filter:
    counted = materialize(count(learn, text, lang), "language-grams")
    totals = counted.groupBy("lang").agg(F.sum("n").alias("total")).orderBy(F.desc("total"), "lang").collect()  # a row per language
    langs = [r["lang"] for r in totals]
    words = max(1, -(-len(langs) // 64))
    bits = np.zeros((SLOTS, words), np.uint64)
    if langs:
        index = F.create_map(*[F.lit(x) for i, r in enumerate(totals) for x in (r["lang"], F.struct(F.lit(i).alias("i"), F.lit(float(r["total"])).alias("total")))])
        rate = counted.select("code", F.element_at(index, F.col("lang")).alias("l"), "n").select("code", "l.i", (F.col("n") / F.col("l.total")).alias("rate"))
        per = rate.where(F.col("rate") >= floor).groupBy("code").agg(F.max("rate").alias("top"), F.collect_list(F.struct("i", "rate")).alias("e"))
        sets = per.select("code", F.explode(F.filter("e", lambda x: x["rate"] >= F.col("top") * share)).alias("x")).select("code", "x.i")

        def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                code, i = b.column(0).to_numpy(), b.column(1).to_numpy().astype(np.int64)
                for at in slots(code):
                    yield pa.RecordBatch.from_pydict({"slot": pa.array(at * words + i // 64), "mask": pa.array((np.uint64(1) << (i % 64).astype(np.uint64)).view(np.int64))})

        got = sets.mapInArrow(place, "slot long, mask long").groupBy("slot").agg(F.bit_or("mask").alias("mask")).toArrow()
        bits.reshape(-1)[got["slot"].to_numpy()] = got["mask"].to_numpy().view(np.uint64)
    drop_table(counted)
    return Filter(langs, bits)


def predict(docs: DataFrame, model: Filter, keep: list[str], text: str = "text") -> DataFrame:
    """The columns ``keep`` with lang_pred and score, for every row of ``docs``."""
    keep = [c for c in keep if c.lower() not in ("lang_pred", "score")]
    docs = without_columns(docs, "lang_pred", "score")
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.bits, model.false_rate()))
    extra = [c for c in keep if c != text]
    schema = docs.select(*keep).schema.add("lang_pred", "string").add("score", "double")

    def tell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        langs, bits, false = shared.value
        for batch in batches:
            texts = batch.column(0)
            best, score = [], []
            for lo, hi in tk.pieces(texts):
                part = texts.slice(lo, hi - lo)
                code, at, ascii_letter = grams(part)
                hits = np.zeros((hi - lo, max(1, len(langs))))
                held = None
                for s in slots(code):
                    held = bits[s] if held is None else held & bits[s]
                n = np.diff(at)
                for i in range(len(langs)):
                    total = np.concatenate([[0], np.cumsum((held[:, i // 64] >> np.uint64(i % 64)).astype(np.uint8) & 1, dtype=np.int64)])
                    hits[:, i] = total[at[1:]] - total[at[:-1]]
                if len(langs):
                    hits = np.clip((hits / np.maximum(n, 1)[:, None] - false) / (1 - false), 0, 1)
                win = hits.argmax(1)
                for i in range(hi - lo):
                    if not langs or not (ascii_letter[i] or any(c.isalpha() for c in part[i].as_py() or "")):
                        best.append(UNKNOWN)
                        score.append(0.0)
                    else:
                        best.append(langs[win[i]])
                        score.append(float(hits[i, win[i]]))
            cols = {c: batch.column(j + 1) for j, c in enumerate(extra)} | {text: texts}
            yield pa.RecordBatch.from_arrays([*(cols[c] for c in keep), pa.array(best, pa.string()), pa.array(score, pa.float64())], [*keep, "lang_pred", "score"])

    return docs.select(text, *extra).mapInArrow(tell, schema)
