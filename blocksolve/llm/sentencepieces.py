"""SentencePiece encoding and decoding, with a max-plus parallel scan for giant documents.

A segmentation is a path whose steps are pieces. In a unigram model a step weighs the piece's
score and the best path wins; in a BPE model the encoding is the only path on which every two
neighbours are stable (merging their joined text gives the same two pieces again), so stable steps
weigh 0 and all others minus infinity. Both are products of matrices over (max, +).

A document of more than ``CHUNK`` characters is cut at fixed places. The states at a cut are the
pieces that can cover the character before it, with how far they reach beyond. Each chunk, on its own,
yields the matrix of best weights from the states at its start to the states at its end; products of these
matrices, taken in a tree, fix the states at every cut; each chunk then traces its own
path back between its two states. Where white space begins after other text no piece can
cross, so inside a chunk only the ends up to the first and from the last such place need the
matrix; the text between them is encoded by the library, as are shorter documents.

Defined results: a null text gives a null list, an empty text an empty list; repeated rows encode
alike; extra columns pass through, but one named like a result is replaced; a character outside the vocabulary falls back to bytes, or to the unknown piece.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StructType

from blocksolve.llm.common import materialize, released, shuffle_partitions, without_columns
from blocksolve.llm.substrings import keyed

CHUNK = 1 << 15
SPACE = "▁"
Start = tuple[int, str]  # reach beyond the cut, piece
CLEAN = (0, "")


class Model:
    """Pieces and scores of a serialized model."""

    def __init__(self, proto: bytes, kind: str = "bpe"):
        import sentencepiece

        self.library = sp = sentencepiece.SentencePieceProcessor()
        sp.LoadFromSerializedProto(proto)
        self.kind = kind
        plain = [i for i in range(sp.vocab_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.ids = {sp.id_to_piece(i): i for i in plain}
        self.scores = {sp.id_to_piece(i): sp.get_score(i) for i in plain}
        self.bytes = {int(sp.id_to_piece(i)[3:5], 16): i for i in range(sp.vocab_size()) if sp.is_byte(i)}
        self.longest = max(map(len, self.ids), default=1)
        self.worst = min(self.scores.values(), default=0.0) - 10
        #: no piece has white space after other text, so such a place is a cut that no piece crosses
        self.cuts = not any(SPACE in p.lstrip(SPACE) for p in self.ids)

    def normalized(self, text: str) -> str:
        return self.library.normalize(text) if text else ""

    @lru_cache(1 << 16)  # noqa: B019  one model a worker
    def merged(self, text: str) -> tuple[str, ...]:
        """BPE of a short string: the best-scored neighbours merge first, leftmost on ties."""
        parts = list(text)
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = self.scores.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return tuple(parts)

    @lru_cache(1 << 18)  # noqa: B019
    def stable(self, left: str, right: str) -> bool:
        return self.merged(left + right) == (left, right) if left else self.merged(right) == (right,)

    def forget(self) -> None:
        """Leaves what a task has learned of neighbours: its worker waits beside those of later stages."""
        self.merged.cache_clear()
        self.stable.cache_clear()
        released()

    def weight(self, left: str, piece: str) -> float | None:
        """Of a step to ``piece`` after ``left`` ('' after a cut); None is minus infinity."""
        if self.kind == "unigram":
            return self.scores.get(piece, self.worst)
        if left and left[-1] not in self.scores and len(left) == 1:
            left = ""  # a character outside the vocabulary never merges
        return 0.0 if self.stable(left, piece) else None

    def steps(self, text: str, at: int) -> Iterator[str]:
        """The pieces that begin at a place; a single character counts even if unknown."""
        yield text[at]
        for end in range(at + 2, min(len(text), at + self.longest) + 1):
            if text[at:end] in self.ids:
                yield text[at:end]

    def ids_of(self, piece: str) -> list[int]:
        if piece in self.ids:
            return [self.ids[piece]]
        return [self.bytes[b] for b in piece.encode()] if self.bytes else [self.library.unk_id()]

    def between_cuts(self, text: str) -> list[int]:
        """Ids of normalized text that begins with white space after a cut."""
        return self.library.encode(text[1:]) if len(text) > 1 else [i for p in self.merged(text) for i in self.ids_of(p)]

    def paths(self, text: str, entries: list[Start], until: int) -> dict:
        """Best paths from entry states at place 0 to the first place at or beyond ``until``.

        {(place, state): {entry: (weight, place before, state before, piece)}}; the state is the last piece for BPE,
        '' for unigram. ``text`` reaches beyond ``until`` by the longest piece, or ends.
        """
        found: dict = {}
        for e in entries:
            found.setdefault((e[0], e[1] if self.kind == "bpe" else ""), {})[e] = (0.0, None, None, None)
        waiting: dict[int, list] = {}
        for key in found:
            waiting.setdefault(key[0], []).append(key)
        at = 0
        while at < min(until, len(text)):
            for key in waiting.pop(at, ()):
                for piece in self.steps(text, at):
                    w = self.weight(key[1], piece)
                    if w is None:
                        continue
                    to = (at + len(piece), piece if self.kind == "bpe" else "")
                    if to not in found:
                        found[to] = {}
                        waiting.setdefault(to[0], []).append(to)
                    for e, had in found[key].items():
                        if e not in found[to] or had[0] + w > found[to][e][0]:
                            found[to][e] = (had[0] + w, key[0], key[1], piece)
            at += 1
        return found

    @staticmethod
    def trace(found: dict, place: int, state: str, entry: Start) -> list[str]:
        out = []
        while True:
            _, place, state, piece = found[(place, state)][entry]
            if piece is None:
                return out[::-1]
            out.append(piece)


class Chunk:
    """One chunk: ``text`` with margins; the chunk is text[before : before + size]."""

    def __init__(self, model: Model, text: str, before: int, size: int, first: bool, last: bool):
        self.model, self.first, self.last = model, first, last
        self.text, self.size, self.back = text[before:], size, text[:before]
        whole = text[max(0, before - 1) :]
        shift = before - max(0, before - 1)
        cut = [i - shift for i in range(max(1, shift), shift + size) if whole[i] == SPACE and whole[i - 1] != SPACE] if model.cuts else []
        cut = [i for i in cut if i >= 0]
        self.head, self.tail = (cut[0], cut[-1]) if cut else (None, None)

    def entries(self) -> list[Start]:
        """States at the start: pieces over the character before it, by how far they reach."""
        if self.first:
            return [CLEAN]
        joined, at = self.back + self.text, len(self.back)
        out = {(b - at, joined[a:b]) for a in range(max(0, at - self.model.longest), at) for b in range(at, min(len(joined), a + self.model.longest) + 1) if b - a == 1 or joined[a:b] in self.model.ids}
        return sorted(out)

    def matrix(self) -> list[tuple[Start, Start, float]]:
        """(state at the start, state at the end, weight), finite entries only."""
        m = self.model
        if self.head is None:
            return [(e, x, w) for e, x, w in self._exits(m.paths(self.text, self.entries(), self.size), 0)]
        into: dict[Start, float] = {}
        for (place, _), by in m.paths(self.text[: self.head], self.entries(), self.head).items():
            if place == self.head:
                for e, (w, *_) in by.items():
                    into[e] = max(w, into.get(e, w))
        rest = self._exits(m.paths(self.text[self.tail :], [CLEAN], self.size - self.tail), self.tail)
        return [(e, x, w + v) for e, w in into.items() for _, x, v in rest]

    def _exits(self, found: dict, base: int) -> list[tuple[Start, Start, float]]:
        out: dict = {}
        for (place, state), by in found.items():
            over = place + base - self.size
            if over < 0 or (self.last and over != 0):
                continue
            for e, (w, _, _, piece) in by.items():
                x = CLEAN if self.last else (over, piece if piece is not None else e[1])
                if (e, x) not in out or w > out[(e, x)]:
                    out[(e, x)] = w
        return [(e, x, w) for (e, x), w in out.items()]

    def ids(self, entry: Start, exit: Start) -> list[int]:
        """Ids of the pieces that begin in this chunk, on the path between two states."""
        m, pieces = self.model, []

        def back(found: dict, entry: Start, end: int, piece: str | None) -> list[str]:
            ends = [(by[entry][0], k) for k, by in found.items() if k[0] == end and entry in by and (piece is None or (by[entry][3] or entry[1]) == piece)]
            return m.trace(found, *max(ends)[1], entry)

        last = None if self.last else exit[1]
        if self.head is None:
            pieces = back(m.paths(self.text, [entry], self.size), entry, self.size + exit[0], last)
            return [i for p in pieces for i in m.ids_of(p)]
        head = back(m.paths(self.text[: self.head], [entry], self.head), entry, self.head, None)
        tail = back(m.paths(self.text[self.tail :], [CLEAN], self.size - self.tail), CLEAN, self.size - self.tail + exit[0], last)
        middle = m.between_cuts(self.text[self.head : self.tail]) if self.tail > self.head else []
        return [i for p in head for i in m.ids_of(p)] + middle + [i for p in tail for i in m.ids_of(p)]


def product(a: list, b: list) -> list:
    """(max, +) product of two matrices with the state between them that attains it: (start, end, weight)."""
    by: dict = {}
    for s, e, w in b:
        by.setdefault(s, []).append((e, w))
    out: dict = {}
    for s, mid, w in a:
        for e, v in by.get(mid, ()):
            if (s, e) not in out or w + v > out[(s, e)]:
                out[(s, e)] = w + v
    return [(s, e, w) for (s, e), w in out.items()]


def states(matrices: list[list]) -> list[Start]:
    """The best path's states at all cuts, outer ends included: a tree of products, then a walk down it."""

    def tree(lo: int, hi: int) -> tuple:
        if hi - lo == 1:
            return matrices[lo], None, None
        mid = (lo + hi) // 2
        a, b = tree(lo, mid), tree(mid, hi)
        return product(a[0], b[0]), a, b

    def walk(node: tuple, s: Start, e: Start) -> list[Start]:
        if node[1] is None:
            return [e]
        left = {x: w for a, x, w in node[1][0] if a == s}
        right = {x: w for x, b, w in node[2][0] if b == e}
        mid = max((x for x in left if x in right), key=lambda x: left[x] + right[x])
        return walk(node[1], s, mid) + walk(node[2], mid, e)

    root = tree(0, len(matrices))
    s, e, _ = max(root[0], key=lambda x: x[2])
    return [s, *walk(root, s, e)]


_MODELS: dict = {}


def loaded(proto: bytes, kind: str) -> Model:
    if (proto, kind) not in _MODELS:
        _MODELS[(proto, kind)] = Model(proto, kind)
    return _MODELS[(proto, kind)]


def _chunks(proto, kind: str, size: int):
    """key, place, of, text, before, length of the chunks of giant texts."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = loaded(proto.value, kind)
        for batch in batches:
            for r in range(batch.num_rows):
                text = model.normalized(batch.column(0)[r].as_py())
                cuts = list(range(0, max(1, len(text)), size))
                rows = []
                for i, a in enumerate(cuts):
                    b = min(len(text), a + size)
                    lo, hi = max(0, a - model.longest), min(len(text), b + model.longest)
                    rows.append((text[lo:hi], a - lo, b - a))
                cols = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([batch.column(1)[r].as_py()] * len(rows), pa.int64()), pa.array([batch.column(2)[r].as_py()] * len(rows), pa.int64()), pa.array(range(len(rows)), pa.int32()),
                     pa.array([len(rows)] * len(rows), pa.int32()), pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int32())],
                    ["_key1", "_key2", "place", "of", "text", "before", "size"],
                )

    return made


_STATE = "struct<reach: int, piece: string>"


def _matrices(proto, kind: str):
    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = loaded(proto.value, kind)
        for batch in batches:
            _key1, _key2, place, of, text, before, size = (c.to_pylist() for c in batch.columns)
            cells = [Chunk(model, text[r], before[r], size[r], place[r] == 0, place[r] == of[r] - 1).matrix() for r in range(len(_key1))]
            kind_of = pa.list_(pa.struct([("s", pa.struct([("reach", pa.int32()), ("piece", pa.string())])), ("e", pa.struct([("reach", pa.int32()), ("piece", pa.string())])), ("w", pa.float64())]))
            rows = [[{"s": {"reach": s[0], "piece": s[1]}, "e": {"reach": e[0], "piece": e[1]}, "w": w} for s, e, w in m] for m in cells]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(rows, kind_of)], ["_key1", "_key2", "place", "cells"])
        model.forget()

    return made


def _paths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From the ordered matrices of a document: its states at both ends of every chunk."""
    state = pa.struct([("reach", pa.int32()), ("piece", pa.string())])
    for batch in batches:
        for r in range(batch.num_rows):
            rows = batch.column(2)[r].as_py()
            at = states([[((c["s"]["reach"], c["s"]["piece"]), (c["e"]["reach"], c["e"]["piece"]), c["w"]) for c in x["cells"]] for x in rows])
            pack = lambda xs: pa.array([{"reach": a, "piece": b} for a, b in xs], state)
            yield pa.RecordBatch.from_arrays(
                [pa.array([batch.column(0)[r].as_py()] * len(rows), pa.int64()), pa.array([batch.column(1)[r].as_py()] * len(rows), pa.int64()), pa.array(range(len(rows)), pa.int32()), pack(at[:-1]), pack(at[1:])],
                ["_key1", "_key2", "place", "entry", "exit"],
            )


def _traced(proto, kind: str):
    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = loaded(proto.value, kind)
        for batch in batches:
            _key1, _key2, place, of, text, before, size, entry, exit = (c.to_pylist() for c in batch.columns)
            ids = [
                Chunk(model, text[r], before[r], size[r], place[r] == 0, place[r] == of[r] - 1).ids((entry[r]["reach"], entry[r]["piece"]), (exit[r]["reach"], exit[r]["piece"])) for r in range(len(_key1))
            ]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(ids, pa.list_(pa.int32()))], ["_key1", "_key2", "place", "ids"])
        model.forget()

    return made


def giant_ids(docs: DataFrame, proto, kind: str, size: int) -> DataFrame:
    """_key1, _key2, ids of the giant texts of ``docs`` (_key1, _key2, text), by the scan."""
    n = shuffle_partitions(docs.sparkSession)
    made = docs.dropDuplicates(["_key1", "_key2"]).select("text", "_key1", "_key2").mapInArrow(_chunks(proto, kind, size), "_key1 long, _key2 long, place int, of int, text string, before int, size int")
    chunks = materialize(made.repartition(n, "_key1", "_key2", "place"), "chunks")
    cells = chunks.mapInArrow(_matrices(proto, kind), f"_key1 long, _key2 long, place int, cells array<struct<s: {_STATE}, e: {_STATE}, w: double>>")
    ordered = cells.groupBy("_key1", "_key2").agg(F.sort_array(F.collect_list(F.struct("place", "cells"))).alias("rows"))
    at = ordered.mapInArrow(_paths, f"_key1 long, _key2 long, place int, entry {_STATE}, exit {_STATE}")
    ids = chunks.join(at, ["_key1", "_key2", "place"]).select("_key1", "_key2", "place", "of", "text", "before", "size", "entry", "exit").mapInArrow(_traced(proto, kind), "_key1 long, _key2 long, place int, ids array<int>")
    return ids.groupBy("_key1", "_key2").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("place", "ids"))), lambda x: x["ids"])).alias("ids"))


def _lists(values: list[list[int] | None]) -> pa.Array:
    flat = np.fromiter(chain.from_iterable(v for v in values if v), np.int32)
    ends = np.concatenate([[0], np.cumsum([len(v) if v else 0 for v in values])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat), mask=pa.array([v is None for v in values], pa.bool_()))


def encode(docs: DataFrame, model_file: str, doc_id: str = "doc_id", text: str = "text", kind: str = "bpe", size: int = CHUNK) -> DataFrame:
    """The rows of ``docs`` with ``ids`` (array<int>)."""
    docs = without_columns(docs, "ids", "_key1", "_key2")
    spark = docs.sparkSession
    with open(model_file, "rb") as f:  # the driver's own file; executors get its bytes
        proto = spark.sparkContext.broadcast(f.read())
    names = docs.columns
    rows = keyed(docs, doc_id, text)
    schema = StructType([docs.schema[c] for c in names]).add("ids", ArrayType(IntegerType()))

    def short(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = loaded(proto.value, kind)
        at = names.index(text)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                texts = part.column(at).to_pylist()
                ids = model.library.encode([t or "" for t in texts], num_threads=1)
                yield pa.RecordBatch.from_arrays([*part.columns, _lists([None if t is None else i for t, i in zip(texts, ids, strict=True)])], schema.names)
        released()

    small = docs.where(F.col(text).isNull() | (F.length(text) <= size)).mapInArrow(short, schema)
    giant = rows.where(F.length(text) > size)
    ids = giant_ids(giant.select(F.col(text).alias("text"), "_key1", "_key2"), proto, kind, size)
    return small.union(giant.join(ids, ["_key1", "_key2"]).select(*names, "ids"))


def decode(encoded: DataFrame, model_file: str, ids: str = "ids", out: str = "decoded", kind: str = "bpe") -> DataFrame:
    """Adds the text of ``ids``; null lists give null."""
    with open(model_file, "rb") as f:
        proto = encoded.sparkSession.sparkContext.broadcast(f.read())
    encoded = without_columns(encoded, out)
    at = encoded.columns.index(ids)
    schema = StructType([*encoded.schema.fields]).add(out, "string")

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        library = loaded(proto.value, kind).library
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                lists = part.column(at).to_pylist()
                texts = library.decode([x or [] for x in lists], num_threads=1) if lists else []
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array([None if x is None else t for x, t in zip(lists, texts, strict=True)], pa.string())], schema.names)

    return encoded.mapInArrow(made, schema)
