"""Language-model scoring by prediction by partial matching (PPM) over bytes, with a word base line.

The model is a trie of byte contexts of up to ``order`` bytes with the counts of the bytes that
follow. A symbol seen n times of T after a context with q distinct symbols has (n - 1/2) / T; q/2
of T is the escape to the next shorter context (the estimator known as method D), where symbols
of the longer context are excluded; the last resort is uniform over the bytes not excluded. Trained
counts nest (a longer context's symbols are among the shorter's), so what is excluded after an
escape depends on the longer context alone: one pair of sums per context makes every code length a few look-ups,
and a batch is scored with array operations.

Counting covers every learning text: a task adds up the (order + 1)-grams of its share and Spark
sums them. The model is all of them, in a written table. Its orders below ``SPLIT`` (256^SPLIT codes
at most, whatever the input) are one trie; the higher orders are tries of one part each, where a part
has all grams with the same last SPLIT context bytes (256^(order + 1 - SPLIT) at most). The ``nodes``
most frequent grams at most (whole bands of counts) are broadcast with their final code lengths; every other
gram of a document, learned or not, is looked up by a join, as (gram, row) pairs that are added up
within each row first. ``nodes`` moves work between the two ways and changes no score.
``adaptive`` instead codes each document with a trie of its own that grows as it goes.

Texts are lower-cased (A-Z). A text is its bytes and one end symbol (byte FF, which UTF-8 never
uses), after ``order`` FF bytes of context. Defined results: a null text is empty and costs its end
symbol; with nothing learned every symbol is uniform; repeated rows score alike.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType

from blocksolve.llm import textkernel as tk
from blocksolve.llm.common import heaviest, join_apart, materialize, released, shuffle_partitions, without_columns
from blocksolve.llm.langid import merged

ORDER = 5
NODES = 1 << 18
HEAD = 1 << 18
SPLIT = 3
CHUNK = 1 << 18  # rows of whole parts that become one trie
COUNTED = 1 << 19  # bytes of text that are counted at once
SENT = 1 << 17  # counts that leave a counting task at once
GRAM, WORD = 0, 1
END_WORD = 0x5E2D58D8B3BCDEF1  # names the end token among word hashes
_U = np.uint64


# --- bytes and codes --------------------------------------------------------------------------


def padded(column: pa.Array, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased bytes, each row between ``order`` FF bytes and one FF; the bounds of rows in them."""
    data, bounds = tk.text_bytes(column)
    low = data.copy()
    low[(low >= 65) & (low <= 90)] += 32
    n = len(bounds) - 1
    step = order + 1
    out = np.full(len(low) + n * step, 0xFF, np.uint8)
    row = np.repeat(np.arange(n), np.diff(bounds))
    out[np.arange(len(low)) + row * step + order] = low
    return out, bounds + np.arange(n + 1) * step


def codes(data: np.ndarray, bounds: np.ndarray, order: int) -> np.ndarray:
    """The (order + 1)-gram that ends at each coded symbol, row after row."""
    n = len(data) - order
    code = np.zeros(max(n, 0), np.uint64)
    for i in range(order + 1):
        code = (code << _U(8)) | data[i : i + n]
    keep = np.ones(len(code), bool)
    for i in range(order):
        keep[bounds[1:-1] - 1 - i] = False  # would span two rows
    return code[keep]


# --- trie -------------------------------------------------------------------------------------


class Lookup:
    """Places of codes in a table: sorted by hash, reached by the hash's leading bits."""

    def __init__(self, keys: np.ndarray):
        self.bits = max(4, int(len(keys)).bit_length() + 1)
        h = self._hash(keys)
        self.order = np.argsort(h, kind="stable")
        self.keys = np.append(keys[self.order], _U(0))
        self.first = np.searchsorted(h[self.order], np.arange((1 << self.bits) + 1).astype(np.uint64)).astype(np.int32)
        self.deepest = int(np.diff(self.first).max(initial=0))

    def _hash(self, keys: np.ndarray) -> np.ndarray:
        return (keys * _U(0x9E3779B97F4A7C15)) >> _U(64 - self.bits)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Place in the stored order, -1 where absent."""
        h = self._hash(keys).astype(np.int64)
        at = self.first[h]
        got = np.where((self.keys[at] == keys) & (at < self.first[h + 1]), at, -1)
        todo = np.flatnonzero((got < 0) & (self.first[h + 1] - at > 1))
        for step in range(1, self.deepest):
            if not len(todo):
                break
            place = at[todo] + step
            inside = place < self.first[h[todo] + 1]
            todo, place = todo[inside], place[inside]
            hit = self.keys[place] == keys[todo]
            got[todo[hit]] = place[hit]
            todo = todo[~hit]
        return got


@dataclass
class Level:
    """Order k: symbols (codes of k + 1 bytes) and contexts (codes of k bytes)."""

    symbols: Lookup
    log_top: np.ndarray  # log10 of the probability if this is the longest known context
    log_half: np.ndarray  # log10(n - 1/2)
    contexts: Lookup
    log_escape: np.ndarray  # from this context, nothing excluded
    log_rest: np.ndarray  # log10 of what the shorter context counts for symbols not seen here (nan: nothing left)
    log_next: np.ndarray  # escape from the shorter context after this one


class Trie:
    """Orders 0 to ``order`` of the grams. With ``base``, its orders are taken as they are and ``code`` may hold whole parts only."""

    def __init__(self, code: np.ndarray, n: np.ndarray, order: int, base: Trie | None = None):
        self.order, self.levels = order, list(base.levels) if base else []
        first = len(self.levels)
        code = code.astype(np.uint64)
        tables = []
        for k in range(order, first - 1, -1):
            code, n = merged([(code & _U((1 << (8 * (k + 1))) - 1), n)]) if len(code) else (code, n)
            tables.append((code, n))
        tables.reverse()
        low = base.top if base else None
        with np.errstate(divide="ignore", invalid="ignore"):
            for k, (code, n) in enumerate(tables, first):
                ctx, inv = np.unique(code >> _U(8), return_inverse=True)
                total, distinct = np.bincount(inv, n, len(ctx)), np.bincount(inv, minlength=len(ctx)).astype(float)
                symbols, contexts = Lookup(code), Lookup(ctx)
                if k:
                    low_code, low_n, low_ctx, low_total, low_distinct = low
                    at = np.searchsorted(low_code, code & _U((1 << (8 * k)) - 1))
                    up = np.searchsorted(low_ctx, ctx & _U((1 << (8 * (k - 1))) - 1)) if k > 1 else np.zeros(len(ctx), np.int64)
                    rest = low_total[up] - np.bincount(inv, low_n[at], len(ctx))
                    fresh = low_distinct[up] - distinct
                    log_rest = np.where(fresh > 0, np.log10(np.maximum(rest, 0.5)), np.nan)
                    log_next = np.where(fresh > 0, np.log10(fresh / 2) - log_rest, 0.0)
                else:
                    log_rest = np.log10(np.maximum(256.0 - distinct, 1))  # order -1: uniform over what is left
                    log_next = np.zeros(len(ctx))
                sort = lambda x, by: np.append(x[by.order], 0.0).astype(np.float32)
                self.levels.append(
                    Level(symbols, sort(np.log10(n - 0.5) - np.log10(total[inv]), symbols), sort(np.log10(n - 0.5), symbols), contexts,
                          sort(np.log10(distinct / 2) - np.log10(total), contexts), sort(log_rest, contexts), sort(log_next, contexts))
                )
                low = code, n, ctx, total, distinct
        self.top = low  # the highest order's counts
        for level in self.levels[first:]:
            level.symbols.order = level.contexts.order = None  # only needed to sort the values

    def log10(self, code: np.ndarray) -> np.ndarray:
        """log10 of the probability of the last byte of each (order + 1)-gram after the others."""
        out = np.zeros(len(code))
        todo = np.arange(len(code))
        above = None  # place of the context escaped from, one order up
        for k in range(self.order, -1, -1):
            level = self.levels[k]
            c = code[todo] & _U((1 << (8 * (k + 1))) - 1)
            at = level.symbols.find(c)
            if above is None:
                fresh = np.ones(len(todo), bool)
            else:
                fresh = above < 0
            hit = at >= 0
            top = hit & fresh
            out[todo[top]] += level.log_top[at[top]]
            if above is not None:
                after = hit & ~fresh
                over = self.levels[k + 1]
                out[todo[after]] += level.log_half[at[after]] - over.log_rest[above[after]]
            miss = ~hit
            here, c = todo[miss], c[miss] >> _U(8)
            ctx = level.contexts.find(c)
            if above is None:
                out[here] += np.where(ctx >= 0, level.log_escape[ctx], 0.0)
            else:
                was = above[miss]
                out[here] += np.where(was >= 0, self.levels[k + 1].log_next[was], np.where(ctx >= 0, level.log_escape[ctx], 0.0))
            todo, above = here, ctx
        if len(todo):
            left = np.where(above >= 0, self.levels[0].log_rest[above], math.log10(256)) if above is not None else math.log10(256)
            out[todo] -= left
        return out


def adaptive(text: str | None, order: int = ORDER) -> float:
    """log10 of the probability of one text under a trie that starts empty and learns each byte after coding it."""
    data = bytes([0xFF] * order) + (text or "").encode().lower() + b"\xff"
    trie: dict[bytes, dict[int, int]] = {}
    total = 0.0
    for i in range(order, len(data)):
        s, out, done = data[i], set(), False
        for k in range(order, -1, -1):
            seen = trie.get(data[i - k : i])
            if not seen:
                continue
            live = {x: n for x, n in seen.items() if x not in out}
            whole = sum(live.values())
            if s in live:
                total += math.log10((live[s] - 0.5) / whole)
                done = True
                break
            if live:
                total += math.log10(len(live) / 2 / whole)
            out |= seen.keys()
        if not done:
            total -= math.log10(max(1, 256 - len(out)))
        for k in range(order + 1):
            at = trie.setdefault(data[i - k : i], {})
            at[s] = at.get(s, 0) + 1
    return total


# --- counting and scoring ---------------------------------------------------------------------


def summed(parts: list) -> tuple[np.ndarray, np.ndarray]:
    """The codes of ``parts``, each once, with their counts added up; the list is emptied. Few arrays of that length are held at once."""
    code, n = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
    parts.clear()
    by = np.argsort(code)
    code, n = code[by], n[by]
    del by
    first = np.flatnonzero(np.append(True, code[1:] != code[:-1])[: len(code)])
    return code[first], np.add.reduceat(n, first) if len(first) else n


def count(learn: DataFrame, text: str = "text", order: int = ORDER) -> DataFrame:
    """kind (GRAM or WORD), code, n: counts of (order + 1)-grams and of word hashes over all rows."""

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = [[], []]
        size = [0, 0]

        def out(kind: int) -> Iterator[pa.RecordBatch]:
            code, n = summed(held[kind])
            size[kind] = 0
            for lo in range(0, len(code), SENT):
                some = code[lo : lo + SENT]
                yield pa.RecordBatch.from_pydict({"kind": pa.array(np.full(len(some), kind, np.int8)), "code": pa.array(some.view(np.int64)), "n": pa.array(n[lo : lo + SENT])})

        for batch in batches:
            for lo, hi in tk.pieces(batch.column(0), COUNTED):
                part = batch.column(0).slice(lo, hi - lo)
                for kind in (GRAM, WORD):
                    values = codes(*padded(part, order), order) if kind == GRAM else np.append(tk.Words(part, lower=True).hash, np.full(hi - lo, END_WORD, np.uint64))
                    held[kind].append(np.unique(values, return_counts=True))
                    size[kind] += len(held[kind][-1][0])
                    if size[kind] > 1 << 21:
                        held[kind].append(summed(held[kind]))
                        size[kind] = len(held[kind][0][0])
                        if size[kind] > 1 << 20:
                            yield from out(kind)
        for kind in (GRAM, WORD):
            if held[kind]:
                yield from out(kind)
        released()

    return learn.select(text).mapInArrow(counts, "kind byte, code long, n long").groupBy("kind", "code").agg(F.sum("n").alias("n"))


def band(n: str) -> Column:
    """Counts in bands of 1/16 of a doubling, rising with the count; 1024 at most."""
    return F.floor(F.log2(F.col(n).cast("double")) * 16).cast("int")


def heads(counted: DataFrame, most: int) -> DataFrame:
    """The rows of the highest bands of counts that hold ``most`` rows at most in all. No task sorts or gathers rows."""
    held = counted.groupBy(band("n").alias("band")).agg(F.count("*").alias("c")).orderBy(F.desc("band")).collect()  # a row a band
    least, total = 1 << 20, 0
    for r in held:
        total += r["c"]
        if total > most:
            break
        least = r["band"]
    return counted.where(band("n") >= least)


@dataclass
class Model:
    order: int
    base: Trie  # orders below SPLIT
    grams: DataFrame  # code, n of every learned (order + 1)-gram
    head: tuple[np.ndarray, np.ndarray]  # the most frequent grams, log10 of their probabilities
    words: DataFrame  # code, n of every learned token
    tokens: int
    distinct: int
    ends: int  # how often the end token was learned: once a text


def train(learn: DataFrame, text: str = "text", order: int = ORDER, nodes: int = NODES) -> Model:
    counted = materialize(count(learn, text, order), "ppm-counts")
    grams = counted.where(F.col("kind") == GRAM).select("code", "n")
    below = min(order, SPLIT - 1)
    low = grams.groupBy(F.col("code").bitwiseAND((1 << (8 * (below + 1))) - 1).alias("code")).agg(F.sum("n").alias("n")).toArrow()
    base = Trie(low["code"].to_numpy().view(np.uint64), low["n"].to_numpy(), below)
    # a learned gram is found at the longest context: its share of that context is all its code length needs
    context = F.shiftrightunsigned("code", 8)
    often = heads(grams, nodes)
    totals = grams.groupBy(context.alias("context")).agg(F.sum("n").alias("total"))
    top = often.withColumn("context", context).join(totals, "context").select("code", "n", "total").toArrow()
    head = top["code"].to_numpy().view(np.uint64), np.log10(top["n"].to_numpy() - 0.5) - np.log10(top["total"].to_numpy())
    words = counted.where(F.col("kind") == WORD).select("code", "n")
    sums = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("tokens"), F.count("*").alias("distinct"), F.coalesce(F.sum(F.when(F.col("code") == np.uint64(END_WORD).view(np.int64).item(), F.col("n"))), F.lit(0)).alias("ends")).first()
    return Model(order, base, grams, head, words, sums["tokens"], sums["distinct"], sums["ends"])


def part_of(code: str) -> Column:
    """The last SPLIT context bytes of a gram."""
    return F.shiftright(code, 8).bitwiseAND((1 << (8 * SPLIT)) - 1)


def answer(asked: DataFrame, model: Model) -> DataFrame:
    """``asked`` (code, c; one row each) with log10, the code's in the whole model; orders of SPLIT and more."""
    shared, order = asked.sparkSession.sparkContext.broadcast(model.base), model.order
    both = model.grams.select("code", "n", F.lit(0).cast("long").alias("c")).unionByName(asked.select("code", F.lit(0).cast("long").alias("n"), "c"))
    dealt = both.withColumn("part", part_of("code")).repartition(shuffle_partitions(asked.sparkSession), "part").sortWithinPartitions("part")

    def told(rows: list[np.ndarray]) -> pa.RecordBatch:
        code, n, c, part = rows
        ask = c > 0
        learned = ~ask & np.isin(part, part[ask])
        trie = Trie(code[learned].view(np.uint64), n[learned], order, shared.value)
        return pa.RecordBatch.from_pydict({"code": pa.array(code[ask]), "c": pa.array(c[ask]), "log10": pa.array(trie.log10(code[ask].view(np.uint64)))})

    def tell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append([x.to_numpy(zero_copy_only=False) for x in batch.columns])
            size += batch.num_rows
            if size > CHUNK:
                rows = [np.concatenate(x) for x in zip(*held)]
                cut = int(np.searchsorted(rows[3], rows[3][-1]))  # the last part may go on
                if cut:
                    yield told([x[:cut] for x in rows])
                held, size = [[x[cut:] for x in rows]], len(rows[3]) - cut
        if size:
            yield told([np.concatenate(x) for x in zip(*held)])
        released()

    return dealt.select("code", "n", "c", "part").mapInArrow(tell, "code long, c long, log10 double")


def score(docs: DataFrame, model: Model, keep: list[str], text: str = "text", head: int = HEAD) -> DataFrame:
    """``keep`` with n_tokens, n_known, base_score (unigram words) and score (the trie), for every row.

    Counts of the ``head`` most frequent words are broadcast (a fixed bound), as are the model's most
    frequent grams; the other words and grams of a document meet theirs in joins, as pairs with the
    row that are added up within each row first.
    """
    made_here = ("n_tokens", "n_known", "base_score", "score", "head_known", "head_log", "head_score", "tail", "__grams", "__times", "__row", "k", "l", "__g")
    docs, keep = without_columns(docs, *made_here), [c for c in keep if c.lower() not in made_here]
    spark = docs.sparkSession
    order, split = model.order, model.order >= SPLIT
    common = heads(model.words, head).toArrow()
    code = common["code"].to_numpy().view(np.uint64)
    sort = np.argsort(code)
    table = Lookup(code[sort])
    counts = np.append(common["n"].to_numpy()[sort][table.order], 0)
    whole_head, ends_known = model.distinct <= head, model.ends
    code, logs = model.head
    sort = np.argsort(code)
    frequent = Lookup(code[sort])
    shared = spark.sparkContext.broadcast((None if split else model.base, frequent, np.append(logs[sort][frequent.order], 0.0), table, counts))
    extra = [c for c in keep if c != text]
    schema = docs.select(*keep).schema.add("n_tokens", "long").add("head_known", "long").add("head_log", "double").add("head_score", "double")
    for c in ("tail", "__grams", "__times"):
        schema = schema.add(c, ArrayType(LongType()))

    def tell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, frequent, log10, words, times = shared.value
        for batch in batches:
            texts = batch.column(0)
            for lo, hi in tk.pieces(texts):
                part = texts.slice(lo, hi - lo)
                data, bounds = padded(part, order)
                ends = bounds - np.arange(hi - lo + 1) * order
                code = codes(data, bounds, order)
                at = frequent.find(code)
                log = np.where(at >= 0, log10[at], 0.0)
                far = np.flatnonzero(at < 0)
                if base:
                    log[far] = base.log10(code[far])
                    far = far[:0]
                logs = np.concatenate([[0.0], np.cumsum(log)])
                row, code = np.searchsorted(ends, far, "right") - 1, code[far]
                by = np.lexsort((code, row))
                row, code = row[by], code[by]
                new = np.flatnonzero(np.append(True, (row[1:] != row[:-1]) | (code[1:] != code[:-1]))[: len(row)])
                gram_at = pa.array(np.searchsorted(row[new], np.arange(hi - lo + 1)).astype(np.int32))
                grams = pa.ListArray.from_arrays(gram_at, pa.array(code[new].view(np.int64)))
                often = pa.ListArray.from_arrays(gram_at, pa.array(np.diff(np.append(new, len(row)))))
                w = tk.Words(part, lower=True)
                at = words.find(w.hash)
                known = at >= 0
                logn = np.concatenate([[0.0], np.cumsum(np.where(known, np.log10(times[at] + 1.0), 0.0))])
                ks = np.concatenate([[0], np.cumsum(known)])
                r = w.row_at
                rare = np.flatnonzero(~known) if not whole_head else np.zeros(0, np.int64)
                tail = pa.ListArray.from_arrays(pa.array(np.searchsorted(rare, r).astype(np.int32)), pa.array(w.hash[rare].view(np.int64)))
                cols = {c: batch.column(j + 1).slice(lo, hi - lo) for j, c in enumerate(extra)} | {text: part}
                yield pa.RecordBatch.from_arrays(
                    [*(cols[c] for c in keep), pa.array(np.diff(r) + 1), pa.array(ks[r[1:]] - ks[r[:-1]] + (ends_known > 0)),
                     pa.array(logn[r[1:]] - logn[r[:-1]] + math.log10(ends_known + 1)), pa.array(logs[ends[1:]] - logs[ends[:-1]]), tail, grams, often],
                    [*keep, "n_tokens", "head_known", "head_log", "head_score", "tail", "__grams", "__times"],
                )
        released()

    part = materialize(docs.select(text, *extra).mapInArrow(tell, schema).withColumn("__row", F.monotonically_increasing_id()), "ppm-scores")
    rare = part.select("__row", F.explode("tail").alias("code")).join(model.words, "code")
    found = rare.select("__row", F.lit(1).alias("k"), F.log10(F.col("n") + 1).alias("l"), F.lit(0.0).alias("__g"))
    if split:
        pairs = part.select("__row", F.explode(F.arrays_zip("__grams", "__times")).alias("x")).select("__row", F.col("x.__grams").alias("code"), F.col("x.__times").alias("times"))
        answers = materialize(answer(pairs.groupBy("code").agg(F.count("*").alias("c")), model), "ppm-answers")
        met = join_apart(pairs, answers, heaviest(answers, "c"), ["code"])
        found = found.unionByName(met.select("__row", F.lit(0).alias("k"), F.lit(0.0).alias("l"), (F.col("times") * F.col("log10")).alias("__g")))
    found = found.groupBy("__row").agg(F.sum("k").alias("k"), F.sum("l").alias("l"), F.sum("__g").alias("__g"))
    denominator = math.log10(model.tokens + 1 * (model.distinct + 1))
    return part.drop("tail", "__grams", "__times").join(found, "__row", "left").select(
        *keep,
        "n_tokens",
        (F.col("head_known") + F.coalesce("k", F.lit(0))).alias("n_known"),
        (F.col("head_log") + F.coalesce("l", F.lit(0.0)) - F.col("n_tokens") * denominator).alias("base_score"),
        (F.col("head_score") + F.coalesce("__g", F.lit(0.0))).alias("score"),
    )
