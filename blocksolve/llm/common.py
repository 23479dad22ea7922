"""Helpers that several operators share: shared-folder tables, salted uniforms, graph classes."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.llm.textkernel import mix
from blocksolve.sources.store import commit as materialize
from blocksolve.sources.store import forget as drop_table


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def without_columns(df: DataFrame, *names: str) -> DataFrame:
    """``df`` without extra columns that are called like what an operator adds: the operator's take their place."""
    taken = {n.lower() for n in names}
    return df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in taken])


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def uniform(*parts: Column) -> Column:
    """A double in (0, 1) fixed by ``parts``: 52 bits of an md5, the same in any SQL engine."""
    hexed = F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 13)
    return (F.conv(hexed, 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(2**52))


#: heaviest keys that joins treat apart; a key not among them holds less than 1 / HOT_KEYS of the rows
HOT_KEYS = 256


def heaviest(keys: DataFrame, count: str) -> DataFrame:
    """The HOT_KEYS rows of ``keys`` (one row a key, narrow) that stand for most rows: a local frame of that size at most."""
    return keys.sparkSession.createDataFrame(keys.orderBy(F.desc(count)).limit(HOT_KEYS).collect(), keys.schema)


def join_apart(rows: DataFrame, keys: DataFrame, hot: DataFrame, on: list[str]) -> DataFrame:
    """Inner join of ``rows`` with ``keys`` (one row a key): rows of the ``hot`` keys stay where they are, the others shuffle."""
    near = rows.join(F.broadcast(hot), on)
    far = rows.join(F.broadcast(hot.select(*on)), on, "left_anti").join(keys, on)
    return near.unionByName(far)


BLOOM_BITS = 1 << 27


class Bloom:
    """Membership of 64-bit keys in 16 MB whatever their number; beyond its size it lets more through, never less."""

    HASHES = 3

    def __init__(self, words: np.ndarray):
        self.words = words

    @classmethod
    def places(cls, keys: np.ndarray):
        h = mix(keys.view(np.uint64))
        for i in range(cls.HASHES):
            yield ((h >> np.uint64(18 * i)) & np.uint64(BLOOM_BITS - 1)).astype(np.int64)

    @classmethod
    def of(cls, keys: DataFrame) -> Bloom:
        """From a frame of one long column. Tasks set bits, Spark merges words; the driver gets at most BLOOM_BITS / 64 rows."""

        def bits(batches):
            for b in batches:
                for p in cls.places(b.column(0).to_numpy(zero_copy_only=False)):
                    yield pa.RecordBatch.from_pydict({"word": pa.array(p >> 6), "mask": pa.array((np.uint64(1) << (p & 63).astype(np.uint64)).view(np.int64))})

        got = keys.mapInArrow(bits, "word long, mask long").groupBy("word").agg(F.bit_or("mask").alias("mask")).toArrow()
        words = np.zeros(BLOOM_BITS >> 6, np.uint64)
        words[got["word"].to_numpy()] = got["mask"].to_numpy().view(np.uint64)
        return cls(words)

    def may_have(self, keys: np.ndarray) -> np.ndarray:
        out = np.ones(len(keys), bool)
        for p in self.places(keys):
            out &= (self.words[p >> 6] >> (p & 63).astype(np.uint64)) & np.uint64(1) > 0
        return out


def components(edges: DataFrame, a: str = "a", b: str = "b", name: str = "cc") -> DataFrame:
    """Connected components of an undirected graph: (node, label), label the least node.

    Alternates large-star and small-star rounds (Kiveris et al. 2014); each round is two
    aggregations whose rows stay within the number of edges, and the edges of the nodes with most
    neighbours do not move in the join. Rounds are written to the shared
    folder, so lineage stays short. The driver reads one aggregate row and HOT_KEYS nodes a round.
    """
    cur = materialize(
        edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u <> v").distinct(), name
    )
    seen = None
    while True:
        both = cur.select("u", "v").union(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        near = materialize(both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"), F.count("*").alias("c")), name)
        large = join_apart(both, near, heaviest(near, "c"), ["u"]).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v")
        low = down.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            down.join(low, "u")
            .select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
            .select("e.u", "e.v")
            .where("u <> v")
            .distinct()
        )
        last, cur = cur, materialize(small, name)
        drop_table(last)
        drop_table(near)
        # order-free digest of the edge set: a fixed point is a forest of stars
        row = cur.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
        if (row["n"], row["x"]) == seen:
            # members and centres through one exchange, so that the result lies evenly over tasks
            both = F.explode(F.array(F.struct(F.col("u").alias("node"), F.col("v").alias("label")), F.struct(F.col("v").alias("node"), F.col("v").alias("label"))))
            return cur.select(both.alias("e")).select("e.node", "e.label").distinct()
        seen = (row["n"], row["x"])


def released() -> None:
    """Gives back what a worker has freed: it waits for its next task beside stages that run without it."""
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)
