"""Exact substring deduplication over words by compaction of a de Bruijn graph.

Every window of ``k`` consecutive words is an edge of the graph. Edges that follow each other in a
text and share their minimizer (the least-hashed run of ``SEED`` words, leftmost on ties) form one path
piece, so a text of n words is about n / 14 rows instead of n. Equal edges share their minimizer,
so they can only meet in one bucket:

1. Pieces whose minimizer occurs once hold no repeated edge and leave.
2. A piece that occurs whole more than once is a repeated path without branches inside: all its edges repeat. Where every
   occurrence of such a piece goes on with the same next piece, and that one occurs as often (so nothing else leads into it), the two
   are one nonbranching path; joins that double the distance to the first piece compact such chains.
3. Where a bucket holds different pieces, paths branch. One source coordinate of each different
   piece fetches its edges from the text there, and edges are counted one by one.
4. One source coordinate of each compacted path fetches its words. A text loses the words of the path at its own coordinates only if they are
   the same words (digests of 128 bits over the words themselves, not over their hashes).

Joins on (minimizer, piece) carry paths and edges back to every source coordinate as spans of words. The rows of the most frequent minimizers, pieces and edges do not move in these joins, so a
passage of a third of all texts does not meet in one task. An edge or piece is named by 128 bits: its minimizer's hash and its own.

Words are ``[^\\x20\\x09-\\x0D]+``, unchanged. Defined results: a null or empty text has no words;
texts shorter than ``k`` words keep everything; repeated rows repeat each other's windows. Rows are
told apart by id and text, so ids may repeat or be null. Extra columns pass through; one
named like a result is replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructType

from blocksolve.llm import textkernel as tk
from blocksolve.llm.common import drop_table, heaviest, join_apart, materialize, without_columns

WINDOW, SEED = 35, 10
_U = np.uint64
_PLACE = _U(28)  # bits of a word's place beside its hash; a text of more words than 2**28 does not fit an Arrow batch


def keyed(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    return docs.withColumns({"_key1": F.coalesce(F.col(doc_id).cast("long"), F.lit(-1)), "_key2": F.xxhash64(text)})


def _minimum(x: np.ndarray, w: int) -> np.ndarray:
    """Least of each w consecutive values."""
    size = 1
    while size * 2 <= w:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    return np.minimum(x[: len(x) - (w - size)], x[w - size :]) if size < w else x


def path_pieces(words: tk.Words, k: int, seed: int) -> tuple[np.ndarray, ...]:
    """minimizer, piece, row, start (word of the row), edges, next piece (0: the text ends) of a batch of texts."""
    h, none = words.hash, np.zeros(0, np.int64)
    nothing = none.astype(np.uint64), none.astype(np.uint64), none, none, none, none.astype(np.uint64)
    if len(h) < k:
        return nothing
    kmers = tk.windows(h, seed)
    place = np.arange(len(kmers)).astype(np.uint64)
    least = _minimum(((kmers >> _PLACE) << _PLACE) | place, k - seed + 1) & _U((1 << 28) - 1)
    row = words.rows()
    at = np.flatnonzero(row[: len(h) - k + 1] == row[k - 1 :])
    if not len(at):
        return nothing
    least, row = least[at].astype(np.int64), row[at]
    new = np.ones(len(at), bool)
    new[1:] = (least[1:] != least[:-1]) | (row[1:] != row[:-1])
    first = np.flatnonzero(new)
    edges = np.diff(np.append(first, len(at)))
    start = at[first]
    up, down = tk.powers(len(h) + 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)])])
    long = edges + k - 1
    piece = tk.mix((total[start + long] - total[start]) * down[start] + long.astype(np.uint64))
    follow = np.append(piece[1:], _U(0))
    follow[np.append(row[first][1:] != row[first][:-1], True)] = 0
    return kmers[least[first]], piece, row[first], start - words.row_at[row[first]], edges, follow


def _pieces_of(k: int, seed: int):
    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in tk.pieces(batch.column(0)):
                m, s, row, start, edges, follow = path_pieces(tk.Words(batch.column(0).slice(lo, hi - lo)), k, seed)
                if len(m):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(m.view(np.int64)), pa.array(s.view(np.int64)), batch.column(1).slice(lo, hi - lo).take(pa.array(row)),
                         batch.column(2).slice(lo, hi - lo).take(pa.array(row)), pa.array(start.astype(np.int32)), pa.array(edges.astype(np.int32)), pa.array(follow.view(np.int64))],
                        ["m", "s", "_key1", "_key2", "start", "edges", "next"],
                    )

    return made


class _Packed:
    """The words of a batch with the one byte of white space after each as a space (none at the end of a row)."""

    def __init__(self, w: tk.Words, keep: np.ndarray | None = None):
        size, after = len(w.data), np.minimum(w.end + 1, np.repeat(w.bounds[1:], np.diff(w.row_at)))
        start, stop = (w.start, after) if keep is None else (w.start[keep], after[keep])
        mark = np.zeros(size + 2, np.int8)
        mark[start] += 1
        np.add.at(mark, stop, -1)
        self.inside = np.cumsum(mark[:size], dtype=np.int8).astype(bool)
        spaced = w.data.copy()
        spaced[tk.SPACE[spaced]] = 0x20
        self.bytes = spaced[self.inside]
        self.at, self.length = np.concatenate([[0], np.cumsum(stop - start)]), w.end - w.start

    def digest(self, first: int, last: int) -> bytes:
        """16 bytes over the words first..last - 1, one space between them."""
        return hashlib.sha1(self.bytes[self.at[first] : self.at[last - 1] + self.length[last - 1]].tobytes()).digest()[:16]


def _told_of(k: int):
    """What is asked of each text (lists of path, m, s, n, start, edges): the edges of pieces, as rows (m, s, off, n, edge), and
    the words of paths, as rows (first half of their digest, s, -1, 0, second half)."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["m", "s", "off", "n", "edge"]
        for batch in batches:
            for lo, hi in tk.pieces(batch.column(0)):
                w = tk.Words(batch.column(0).slice(lo, hi - lo))
                name = tk.windows(w.hash, k)
                part = batch.column(1).slice(lo, hi - lo)
                ask = part.flatten()
                path, m, s, n, start, edges = (ask.field(i).to_numpy(zero_copy_only=False) for i in range(6))
                path = path.astype(bool)
                begin = w.row_at[np.repeat(np.arange(hi - lo), part.value_lengths().to_numpy(zero_copy_only=False))] + start
                if path.any():
                    packed = _Packed(w)
                    d = np.frombuffer(b"".join(packed.digest(a, a + e + k - 1) for a, e in zip(begin[path], edges[path], strict=True)), np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(d[::2]), pa.array(s[path]), pa.array(np.full(len(d) // 2, -1, np.int32)), pa.array(np.zeros(len(d) // 2, np.int64)), pa.array(d[1::2])], names)
                m, s, n, begin, edges = (x[~path] for x in (m, s, n, begin, edges))
                of = np.repeat(np.arange(len(m)), edges)
                off = np.arange(len(of)) - np.repeat(np.cumsum(edges) - edges, edges)
                edge = name[begin[of] + off]
                for a in range(0, len(of), 1 << 18):
                    b = slice(a, a + (1 << 18))
                    yield pa.RecordBatch.from_arrays([pa.array(m[of[b]]), pa.array(s[of[b]]), pa.array(off[b].astype(np.int32)), pa.array(n[of[b]]), pa.array(edge[b].view(np.int64))], names)

    return made


def compacted(whole: DataFrame) -> DataFrame:
    """m, s, n, at, edges of the nonbranching paths: of each chain of repeated pieces its first, with the edges of all.

    ``whole``: m, s, n, at, edges, next, other (least and greatest next piece). Each round doubles how far a piece sees back, so a
    chain of c pieces takes log2(c) rounds; a text that ends ends its chains, so there are no cycles.
    """
    again = whole.where("n > 1")
    ahead = again.where("next = other AND next <> 0").select(F.col("next").alias("s"), F.col("s").alias("head"), F.col("n").alias("n2"), F.col("edges").cast("long").alias("far"))
    back = again.select("s", "n").join(ahead, "s").where("n = n2 AND s <> head").select("s", "head", "far")
    back = materialize(back.dropDuplicates(["s"]), "chains")
    moved = not back.isEmpty()
    while moved:
        seen = back.select(F.col("s").alias("head"), F.col("head").alias("head2"), F.col("far").alias("far2"))
        far = back.select("s", "head", "far").join(seen, "head", "left").select(
            "s", F.coalesce("head2", "head").alias("head"), (F.col("far") + F.coalesce("far2", F.lit(0))).alias("far"), F.col("head2").isNotNull().alias("moved")
        )
        last, back = back, materialize(far, "chains")
        drop_table(last)
        moved = not back.where("moved").isEmpty()
    ends = again.select("s", "edges").join(back, "s").groupBy(F.col("head").alias("s")).agg(F.max(F.col("far") + F.col("edges")).alias("whole"))
    heads = again.join(back.select("s"), "s", "left_anti").join(ends, "s", "left")
    return heads.select("m", "s", "n", "at", F.coalesce("whole", "edges").cast("int").alias("edges"))


def repeated_spans(docs: DataFrame, k: int = WINDOW, seed: int = SEED) -> DataFrame:
    """_key1, _key2, spans (code, d1, d2): per text with repeated windows, its words in them as codes begin * 2**32 + end (they may overlap),
    and the digest that the words of a path must have (0, 0: a single edge, which is named by 128 bits).

    ``docs`` has _key1, _key2, doc_id and text.
    """
    pieces = materialize(docs.select("text", "_key1", "_key2").mapInArrow(_pieces_of(k, seed), "m long, s long, _key1 long, _key2 long, start int, edges int, next long"), "pieces")
    again = materialize(pieces.groupBy("m").agg(F.count("*").alias("c")).where("c > 1"), "again")
    met = materialize(join_apart(pieces, again, heaviest(again, "c"), ["m"]).drop("c"), "met")
    drop_table(pieces)
    whole = met.groupBy("m", "s").agg(F.count("*").alias("n"), F.min(F.struct("_key1", "_key2", "start", "edges")).alias("at"), F.min("next").alias("next"), F.max("next").alias("other"))
    whole = materialize(whole.withColumn("edges", F.col("at.edges")), "pieces-once")
    paths = materialize(compacted(whole), "paths")
    forks = materialize(whole.groupBy("m").agg(F.count("*").alias("c")).where("c > 1"), "forks")
    ask = lambda df, path: df.select("at._key1", "at._key2", F.struct(F.lit(path).alias("path"), "m", "s", "n", F.col("at.start").alias("start"), "edges").alias("ask"))
    asked = ask(join_apart(whole, forks, heaviest(forks, "c"), ["m"]), False).union(ask(paths, True)).groupBy("_key1", "_key2").agg(F.collect_list("ask").alias("ask"))
    # repeated rows answer the same question twice, hence distinct
    told = docs.join(asked, ["_key1", "_key2"]).select("text", "ask").mapInArrow(_told_of(k), "m long, s long, off int, n long, edge long").distinct()
    told = materialize(told, "told")
    edges = told.where("off >= 0")
    many = edges.groupBy("m", "edge").agg(F.sum("n").alias("c"), F.max(F.col("n") == 1).alias("once")).where("c > 1 AND once").select("m", "edge", "c")
    many = materialize(many, "many")
    none = F.lit(0).cast("long")
    partly = join_apart(edges.where("n = 1"), many, heaviest(many, "c"), ["m", "edge"]).groupBy("m", "s").agg(F.collect_list("off").alias("offs"))
    partly = partly.select("m", "s", "offs", F.lit(1).alias("long"), none.alias("d1"), none.alias("d2"))
    words = told.where("off < 0").select("s", F.col("m").alias("d1"), F.col("edge").alias("d2"))
    known = materialize(paths.select("m", "s", "n", F.col("edges").alias("long")).join(words, "s"), "known")
    path = lambda df: df.select("m", "s", F.array(F.lit(0)).alias("offs"), "long", "d1", "d2")
    span = lambda o: F.struct((F.shiftleft((F.col("start") + o).cast("long"), 32) + F.col("start") + o + F.col("long") + (k - 1)).alias("code"), "d1", "d2")
    found = join_apart(met, path(known).union(partly), path(heaviest(known, "n")), ["m", "s"])
    return found.select("_key1", "_key2", F.explode(F.transform("offs", span)).alias("span")).groupBy("_key1", "_key2").agg(F.collect_set("span").alias("spans"))


def cut(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", k: int = WINDOW, seed: int = SEED) -> DataFrame:
    """The rows of ``docs`` with n_words, n_removed, kept_sha256 and kept (the text without its repeated words).

    ``kept`` has the words left with the white space that followed each; the digest is over the
    words joined by one space.
    """
    docs = without_columns(docs, "kept", "n_words", "n_removed", "kept_sha256", "_key1", "_key2", "spans")
    names = [c for c in docs.columns if c != text]
    known = keyed(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), "doc_id", "text")
    spans = repeated_spans(known, k, seed)
    whole = keyed(docs, doc_id, text)
    schema = StructType([docs.schema[c] for c in names]).add("kept", StringType()).add("n_words", LongType()).add("n_removed", LongType()).add("kept_sha256", StringType())

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in tk.pieces(batch.column(0)):
                rows = batch.slice(lo, hi - lo)
                kept, words, removed, digest = without(rows.column(0), rows.column(1))
                yield pa.RecordBatch.from_arrays([*rows.columns[2:], kept, words, removed, digest], schema.names)

    return whole.join(spans, ["_key1", "_key2"], "left").select(text, "spans", *names).mapInArrow(made, schema)


def without(texts: pa.Array, spans: pa.Array) -> tuple[pa.Array, pa.Array, pa.Array, pa.Array]:
    """kept, n_words, n_removed, kept_sha256 of each text, given its spans."""
    w = tk.Words(texts)
    n = len(w.start)
    lengths = spans.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    code, d1, d2 = (spans.flatten().field(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(3))
    base = np.repeat(w.row_at[:-1], lengths)
    first, last = base + (code >> 32), base + (code & 0xFFFFFFFF)
    check = np.flatnonzero((d1 != 0) | (d2 != 0))
    if len(check):
        packed = _Packed(w)
        mine = np.frombuffer(b"".join(packed.digest(a, b) for a, b in zip(first[check], last[check], strict=True)), np.int64)
        same = np.ones(len(code), bool)
        same[check] = (mine[::2] == d1[check]) & (mine[1::2] == d2[check])
        first, last = first[same], last[same]
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, first, 1)
    np.add.at(edge, last, -1)
    gone = np.cumsum(edge[:-1]) > 0
    lost = np.concatenate([[0], np.cumsum(gone)])
    n_words, n_removed = np.diff(w.row_at), lost[w.row_at[1:]] - lost[w.row_at[:-1]]
    left = _Packed(w, ~gone)
    at, size = np.concatenate([[0], np.cumsum(left.inside)])[w.bounds], len(w.data)
    digest = [hashlib.sha256(left.bytes[a:b].tobytes().rstrip(b" ")).hexdigest() for a, b in zip(at[:-1], at[1:], strict=True)]
    # text: drop from each removed word to the next word, or to the end of the row
    drop = np.zeros(size + 1, np.int8)
    follow = np.append(w.start[1:], size)
    stop = np.minimum(follow, np.repeat(w.bounds[1:], n_words))
    drop[w.start[gone]] += 1
    np.add.at(drop, stop[gone], -1)
    stay = np.cumsum(drop[:size], dtype=np.int8) == 0
    left, at = w.data[stay].tobytes(), np.concatenate([[0], np.cumsum(stay)])[w.bounds]
    kept = pa.StringArray.from_buffers(len(texts), pa.py_buffer(at.astype(np.int32)), pa.py_buffer(left))
    return kept, pa.array(n_words), pa.array(n_removed), pa.array(digest, pa.string())


ORACLE = r"""
WITH split AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
starts AS (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM split WHERE len(w) >= 35),
named AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 34], ' ')) AS name FROM starts),
again AS (SELECT doc_id, i FROM named QUALIFY count(*) OVER (PARTITION BY name) > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS pos, true AS lost FROM again),
words AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS pos FROM split),
counted AS (
  SELECT doc_id, count(*) AS n_words, count(lost) AS n_removed, string_agg(word, ' ' ORDER BY pos) FILTER (WHERE lost IS NULL) AS kept
  FROM words LEFT JOIN gone USING (doc_id, pos) GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(n_words, 0) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM documents d LEFT JOIN counted USING (doc_id)
"""
