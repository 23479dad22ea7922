"""N-gram Jaccard join with a MinHash LSH forest and exact verification.

A text's shingles are its distinct runs of ``n`` words (a text of fewer words has one, of all its
words). Texts with equal shingle sets are copies: one node with a number of copies. Each node puts a signature of as many MinHash
values as ``WIDTHS`` has levels into each of ``TREES`` tries. A signature is one number, its first value in the leading bits, so a trie is the sorted order
of its signatures, which Spark deals by ranges: no bucket, however large, has to lie in one task.

A node first matches those that share its whole signature in some trie; then the matched prefix is shortened level by level, until a partner at
the least similarity that a link of this node can have is met in some trie with the target recall (1 - (1 - s^d)^TREES). That s is the threshold for most nodes
and more for small sets, as only few similarities can occur there (one of 6 shingles has links from 5/6 on; one of 3 has none and never
matches). Where two nodes meet, both have come down to that depth. Nodes of a run of equal prefixes join its first
node, so a run of m nodes is m - 1 links, never all pairs; the connected cells of those links hold all candidates.

Inside a cell every pair is verified exactly: nodes fall into narrow classes of set size, and classes, in order of size, into
blocks of about ``BLOCK`` nodes and ``LOAD`` shingles (a larger class is dealt by hash into several; a block holds the
ends of two at most). Each pair of blocks that the size ratio allows is one group of set intersections (a product
of 0/1 matrices over the shingles that occur twice). It returns per node how many links it found and one row to its
local class, so rows stay in proportion to nodes, though every link is counted. Classes are the connected components.

Defined results: a null text, or one without words, has no links and is a class of its own; copies count as links of
each other; class_id is the least doc_id of the class; repeated rows are copies; rows whose ids are
null carry the least other id of their class, or null. Extra columns pass through ``dedup`` only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksolve.llm import textkernel as tk
from blocksolve.llm.common import Bloom, components, drop_table, heaviest, join_apart, materialize, shuffle_partitions, without_columns
from blocksolve.llm.substrings import keyed

TREES, RECALL = 20, 0.999
WIDTHS = (10, 10, 10, 10, 10, 5, 5, 4)  # bits of the levels of a signature
DEPTH = len(WIDTHS)
SMALL = 256  # sizes of sets that are told apart in the choice of the depth
BLOCK, LOAD = 256, 1 << 20
CLASSES = 16  # of set size to a doubling
SALT = 32  # parts of the pairs of blocks of a cell
_RNG = np.random.Generator(np.random.PCG64(31))
_XOR = _RNG.integers(0, 2**32, TREES * DEPTH, dtype=np.uint64).astype(np.uint32)
_MUL = _RNG.integers(0, 2**32, TREES * DEPTH, dtype=np.uint64).astype(np.uint32) | np.uint32(1)


def depth_for(similarity: float, recall: float = RECALL, trees: int = TREES, deepest: int = DEPTH) -> int:
    """The longest prefix that still reaches the recall; 1 if none does."""
    d = deepest
    while d > 1 and 1 - (1 - similarity**d) ** trees < recall:
        d -= 1
    return d


def least_similarity(size: int, threshold: float) -> float:
    """The least similarity from the threshold on that a set of ``size`` shingles can have with a different one; above 1 if there is none."""
    found = 2.0
    for other in range(int(size * threshold), int(size / threshold) + 2):
        for common in range(max(0, int(threshold * max(size, other)) - 1), min(size, other) + 1):
            union = size + other - common
            if common < union and common >= threshold * union - 1e-6:
                found = min(found, common / union)
    return found


def depths(threshold: float, recall: float) -> np.ndarray:
    """The depth that a node of each size (the last: that size or more) comes down to; DEPTH + 1 where no link is possible."""
    least = [least_similarity(size, threshold) for size in range(SMALL)] + [threshold]
    return np.array([DEPTH + 1 if s > 1 else depth_for(s, recall) for s in least], np.int8)


def shingles(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word n-grams of all rows (repeats included), and the bounds of the rows in them."""
    w = tk.Words(column)
    count = np.diff(w.row_at)
    own = np.where(count >= n, count - n + 1, np.minimum(count, 1))
    bounds = np.concatenate([[0], np.cumsum(own)])
    out = np.zeros(bounds[-1], np.uint64)
    runs = tk.windows(w.hash, n)
    if len(runs):
        row = w.rows()
        at = np.flatnonzero(row[: len(runs)] == row[n - 1 :])
        full = np.repeat(count >= n, own)
        out[full] = runs[at]
    for r in np.flatnonzero((count > 0) & (count < n)):
        h = w.hash[w.row_at[r] : w.row_at[r + 1]]
        out[bounds[r]] = tk.windows(h, len(h))[0] + np.uint64(len(h))
    return out, bounds


def signatures(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Per row without gaps (every row has a shingle) its signatures in all tries."""
    h = (hashes >> np.uint64(32)).astype(np.uint32)
    out = np.zeros((TREES, len(bounds) - 1), np.uint64)
    for t in range(TREES):
        for d, width in enumerate(WIDTHS):
            i = t * DEPTH + d
            low = np.minimum.reduceat((h ^ _XOR[i]) * _MUL[i], bounds[:-1])
            out[t] = (out[t] << np.uint64(width)) | (tk.mix(low + np.uint64(i << 32)) >> np.uint64(64 - width))
    return out.T


def nodes_of(docs: DataFrame, n: int) -> DataFrame:
    """doc_id, _key1, _key2, node (null without words), size (distinct shingles), sigs of each row of ``docs``."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in tk.pieces(batch.column(0)):
                h, at = shingles(batch.column(0).slice(lo, hi - lo), n)
                some = np.flatnonzero(np.diff(at))
                node, size = np.zeros(hi - lo, np.uint64), np.zeros(hi - lo, np.int32)
                for r in some:
                    own = np.unique(h[at[r] : at[r + 1]])
                    size[r] = len(own)
                    node[r] = tk.mix(own).sum(dtype=np.uint64)
                sigs = signatures(h, at[np.append(some, hi - lo)]) if len(some) else np.zeros((0, TREES), np.uint64)
                filled = np.zeros(hi - lo + 1, np.int32)
                filled[1:][some] = TREES
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(c).slice(lo, hi - lo) for c in (1, 2, 3)), pa.array(node.view(np.int64), mask=size == 0), pa.array(size),
                     pa.ListArray.from_arrays(pa.array(np.cumsum(filled, dtype=np.int32)), pa.array(sigs.reshape(-1).view(np.int64)))],
                    ["doc_id", "_key1", "_key2", "node", "size", "sigs"],
                )

    return docs.select("text", "doc_id", "_key1", "_key2").mapInArrow(made, "doc_id long, _key1 long, _key2 long, node long, size int, sigs array<long>")


def _matches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (tree, sig, node, depth) in the order of the tries. Gives links (level 0: node, hub), and of each level the first and the last
    run (tree, level, prefix, hub), which may go on in the rows before and after."""
    for batch in batches:
        tree, sig, node, depth = (batch.column(c).to_numpy(zero_copy_only=False) for c in range(4))
        hub, out = node.copy(), []
        for level in range(DEPTH, int(depth.min(initial=DEPTH + 1)) - 1, -1):
            at = np.flatnonzero(depth <= level)
            if not len(at):
                continue
            t, prefix = tree[at], sig[at] >> sum(WIDTHS[level:])
            first = np.append(True, (t[1:] != t[:-1]) | (prefix[1:] != prefix[:-1]))
            head = node[at][np.maximum.accumulate(np.where(first, np.arange(len(at)), 0))]
            new = np.flatnonzero((head != hub[at]) & (head != node[at]))
            hub[at] = head
            zero = np.zeros(len(new), np.int8)
            out.append((zero, zero, node[at][new], head[new]))
            ends = np.array([0, -1])
            out.append((t[ends], np.full(2, level, np.int8), prefix[ends], head[ends]))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], ["tree", "level", "a", "hub"])


def cells(nodes: DataFrame, threshold: float, recall: float) -> DataFrame:
    """node, cell: connected candidates, from the signatures of ``nodes``."""
    table = F.array(*[F.lit(int(d)) for d in depths(threshold, recall)])
    one = nodes.where("node IS NOT NULL").groupBy("node").agg(F.first("size").alias("size"), F.first("sigs").alias("sigs"))
    one = one.withColumn("depth", F.get(table, F.least("size", F.lit(SMALL))).cast("byte")).where(F.col("depth") <= DEPTH)
    sorted_ = one.select("node", "depth", F.posexplode("sigs").alias("t", "sig")).select(F.col("t").cast("byte").alias("tree"), "sig", "node", "depth")
    sorted_ = sorted_.repartitionByRange(shuffle_partitions(nodes.sparkSession), "tree", "sig", "node").sortWithinPartitions("tree", "sig", "node")
    met = materialize(sorted_.mapInArrow(_matches, "tree byte, level byte, a long, hub long"), "matches")
    # runs that go on in another batch: a few rows a batch
    runs = met.where("level > 0")
    across = runs.join(runs.groupBy("tree", "level", "a").agg(F.min("hub").alias("least")), ["tree", "level", "a"]).where("hub <> least").select(F.col("hub").alias("node"), F.col("least").alias("hub"))
    links = met.where("level = 0").select(F.col("a").alias("node"), "hub").union(across).distinct()
    found = components(links, "node", "hub", "cells").withColumnRenamed("label", "cell")
    return found


def _sets_of(n: int, wanted):
    """The shingle sets of the texts that ``wanted`` (a broadcast Bloom filter of text hashes) may hold."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            batch = whole.filter(pa.array(wanted.value.may_have(whole.column(2).to_numpy(zero_copy_only=False))))
            for lo, hi in tk.pieces(batch.column(0)):
                h, at = shingles(batch.column(0).slice(lo, hi - lo), n)
                sets = [np.unique(h[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
                ends = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
                flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, hi - lo) for c in (1, 2)), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.view(np.int64)))], ["_key1", "_key2", "set"])

    return made


def pair_links(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Positions (into left, into right) of linked pairs of sets; left and right are positions into ``sets``."""
    size = np.array([len(s) for s in sets])
    inter = np.zeros((len(left), len(right)), np.float32)
    if len(sets) == 2:
        inter[:] = len(np.intersect1d(*sets, assume_unique=True))
        if len(left) == 2:
            inter[:] = np.where(np.eye(2, dtype=bool), size[:, None], inter)
    else:
        flat = np.concatenate(sets)
        owner = np.repeat(np.arange(len(sets)), size)
        order = np.argsort(flat, kind="stable")
        flat, owner = flat[order], owner[order]
        new = np.concatenate([[True], flat[1:] != flat[:-1]])
        column = np.cumsum(new) - 1
        twice = np.bincount(column)[column] > 1
        owner, column = owner[twice], column[twice]
        if len(column):
            column = np.concatenate([[0], np.cumsum(column[1:] != column[:-1])])
        width = 4096
        cuts = np.searchsorted(column, np.arange(0, (column[-1] + 1 if len(column) else 0) + width, width)) if len(column) else []
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            x = np.zeros((len(sets), width), np.float32)
            x[owner[a:b], column[a:b] - column[a] // width * width] = 1
            inter += x[left] @ x[right].T
    union = size[left][:, None] + size[right][None, :] - inter
    return np.nonzero(inter >= threshold * union - 1e-6)


def _verify(threshold: float):
    """Rows sorted by (cell, i, j): the members of two blocks. Gives node, hub, links, linked (copies weighed)."""

    def task(key: tuple, node: np.ndarray, block: np.ndarray, copies: np.ndarray, sets: list[np.ndarray]) -> pa.RecordBatch:
        i, j = key[1], key[2]
        left, right = np.flatnonzero(block == i), np.flatnonzero(block == j)
        a, b = pair_links(sets, left, right, threshold)
        a, b = left[a], right[b]
        if i == j:
            a, b = a[a < b], b[a < b]
        at, to = np.concatenate([a, b]), np.concatenate([b, a])
        links = np.bincount(at, minlength=len(node))
        linked = np.bincount(at, copies[to], len(node)).astype(np.int64)
        hub = node.copy()
        while len(a):
            low = np.minimum(hub[a], hub[b])
            if (hub[a] == low).all() and (hub[b] == low).all():
                break
            np.minimum.at(hub, a, low)
            np.minimum.at(hub, b, low)
        some = np.flatnonzero(links)
        return pa.RecordBatch.from_arrays([pa.array(x[some]) for x in (node, hub, links, linked)], ["node", "hub", "links", "linked"])

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []

        def flush() -> pa.RecordBatch:
            return task(key, *(np.array([h[c] for h in held]) for c in range(3)), [h[3] for h in held])

        for batch in batches:
            cell, i, j, node, block, copies = (batch.column(c).to_numpy(zero_copy_only=False) for c in range(6))
            ends, flat = batch.column(6).offsets.to_numpy(), batch.column(6).values.to_numpy(zero_copy_only=False)
            for r in range(batch.num_rows):
                now = (cell[r], i[r], j[r])
                if now != key:
                    if held:
                        yield flush()
                    key, held = now, []
                held.append((node[r], block[r], copies[r], flat[ends[r] : ends[r + 1]].copy()))
        if held:
            yield flush()

    return made


def links_of(docs: DataFrame, nodes: DataFrame, n: int, threshold: float, recall: float = RECALL) -> DataFrame:
    """node, hub, links, linked: partial sums and local classes of all verified links between different texts."""
    member = cells(nodes, threshold, recall).join(
        nodes.where("node IS NOT NULL").groupBy("node").agg(F.count("*").alias("copies"), F.first("size").alias("size"), F.min(F.struct("_key1", "_key2")).alias("at")), "node"
    )
    told = materialize(member.select("cell", "node", "copies", "size", F.floor(F.log2("size") * CLASSES).cast("int").alias("class"), "at._key1", "at._key2"), "sized")
    kinds = told.groupBy("cell", "class").agg(F.count("*").alias("c"), F.sum("size").alias("load"))
    # at most CLASSES * 31 rows a cell, however many nodes it has
    before = Window.partitionBy("cell").orderBy("class").rowsBetween(Window.unboundedPreceding, -1)
    blocks = lambda c, load: F.greatest(F.col(c) / BLOCK, F.col(load) / LOAD)
    kinds = kinds.withColumns({"c0": F.coalesce(F.sum("c").over(before), F.lit(0)), "load0": F.coalesce(F.sum("load").over(before), F.lit(0))})
    kinds = materialize(kinds.select("cell", "class", "c", F.floor(blocks("c0", "load0")).alias("base"), F.ceil(blocks("c", "load")).alias("parts")), "kinds")
    block = (F.col("base") + F.pmod(F.xxhash64("node"), "parts")).cast("int")
    member = join_apart(told, kinds, heaviest(kinds, "c"), ["cell", "class"]).select("cell", "node", "copies", "size", "_key1", "_key2", block.alias("block"))
    member = materialize(member, "members")
    drop_table(told)
    span = member.groupBy("cell", "block").agg(F.min("size").alias("lo"), F.max("size").alias("hi"), F.count("*").alias("members"))
    # a row per 256 nodes or so; the pairs of a cell are made in SALT parts
    left = span.select("cell", F.pmod("block", F.lit(SALT)).alias("salt"), F.col("block").alias("i"), "hi", F.col("members").alias("m"))
    right = span.select("cell", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("salt"), F.col("block").alias("j"), "lo")
    pairs = left.join(right, ["cell", "salt"]).where((F.col("i") <= F.col("j")) & (F.col("hi") >= threshold * F.col("lo")) & ((F.col("i") < F.col("j")) | (F.col("m") > 1)))
    pairs = pairs.select("cell", "i", "j")
    goes = pairs.select("cell", "i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    # texts stay where they are: a filter of bounded size lets nearly only members' sets move on, and the join is exact
    wanted = docs.sparkSession.sparkContext.broadcast(Bloom.of(member.select("_key2")))
    sets = docs.select("text", "_key1", "_key2").mapInArrow(_sets_of(n, wanted), "_key1 long, _key2 long, set array<long>")
    sets = sets.join(member.select("_key1", "_key2", "cell", "node", "block", "copies"), ["_key1", "_key2"]).dropDuplicates(["node"])
    dealt = sets.join(goes, ["cell", "block"])
    dealt = dealt.select("cell", "i", "j", "node", "block", "copies", "set").repartition(shuffle_partitions(docs.sparkSession), "cell", "i", "j").sortWithinPartitions("cell", "i", "j")
    return dealt.mapInArrow(_verify(threshold), "node long, hub long, links long, linked long")


def join(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", n: int = 5, threshold: float = 0.8, recall: float = RECALL) -> DataFrame:
    """doc_id, _key2, class_id, copy_of, n_links for every row: links to copies and to similar texts, all counted."""
    known = keyed(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), "doc_id", "text")
    nodes = materialize(nodes_of(known, n), "nodes")
    found = materialize(links_of(known, nodes, n, threshold, recall), "links")
    label = components(found, "node", "hub", "classes")
    per = nodes.where("node IS NOT NULL").groupBy("node").agg(F.count("*").alias("copies"), F.min("doc_id").alias("copy_of"))
    linked = found.groupBy("node").agg(F.sum("linked").alias("linked"))
    per = materialize(per.join(linked, "node", "left").join(label, "node", "left").withColumn("label", F.coalesce("label", "node")), "per-node")
    # a class may hold a third of all nodes and a node a third of all rows: the rows of the heaviest stay where they are
    first = materialize(per.groupBy("label").agg(F.min("copy_of").alias("class_id"), F.count("*").alias("c")), "classes-first")
    told = join_apart(per, first, heaviest(first, "c"), ["label"])
    told = materialize(told.select("node", "class_id", "copy_of", "copies", (F.col("copies") - 1 + F.coalesce("linked", F.lit(0))).alias("n_links")), "told")
    rows = nodes.select("doc_id", "_key1", "_key2", "node")
    placed = join_apart(rows.where("node IS NOT NULL"), told, heaviest(told, "copies"), ["node"])
    alone = rows.where("node IS NULL").select("doc_id", "_key2", F.col("doc_id").alias("class_id"), F.col("doc_id").alias("copy_of"), F.lit(0).cast("long").alias("n_links"))
    return placed.select("doc_id", "_key2", "class_id", "copy_of", F.col("n_links").cast("long").alias("n_links")).unionByName(alone)


def dedup(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of ``docs`` with the first document of each class (least doc_id; of rows equal in it, one). Rows without words all stay."""
    docs = without_columns(docs, "_key1", "_key2")
    found = join(docs, doc_id, text, **how)
    away = found.where("class_id IS NOT NULL AND NOT (doc_id <=> class_id)").select(F.coalesce("doc_id", F.lit(-1)).alias("_key1"), "_key2").distinct()
    wordy = F.coalesce(F.col(text).rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    kept = keyed(docs.where(wordy), doc_id, text).join(away, ["_key1", "_key2"], "left_anti")
    return kept.dropDuplicates(["_key1", "_key2"]).select(docs.columns).unionByName(docs.where(~wordy))


#: all pairs that share a shingle, compared exactly; classes by following links
ORACLE = r"""
WITH RECURSIVE split AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
grams AS (
  SELECT doc_id, hash(unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END)) AS g
  FROM split),
sets AS (SELECT DISTINCT doc_id, g FROM grams),
sizes AS (SELECT doc_id, count(*) AS n FROM sets GROUP BY doc_id),
meets AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM sets a JOIN sets b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
links AS (
  SELECT a, b, common = x.n AND common = y.n AS same FROM meets JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b
  WHERE 10 * common >= 8 * (x.n + y.n - common)),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b),
class AS (SELECT a AS doc_id, min(b) AS class_id FROM reach GROUP BY a),
per AS (SELECT a AS doc_id, count(*) AS n_links, min(b) FILTER (WHERE same) AS least FROM links GROUP BY a)
SELECT d.doc_id, class_id, least(d.doc_id, coalesce(p.least, d.doc_id)) AS copy_of, CAST(coalesce(n_links, 0) AS BIGINT) AS n_links
FROM documents d JOIN class USING (doc_id) LEFT JOIN per p USING (doc_id)
"""
