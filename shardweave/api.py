"""The user's surface: tables of vectors, indexes over them, and their merge."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import quality, search, tower
from shardweave.plans import builders, fuse
from shardweave.sources import store, tables
from shardweave.staging import stage


class VectorTable:
    """Vectors ``(vec_id, x)`` of a frame and a metric; rows that can't be indexed are in ``rejects (vec_id, reason)``."""

    def __init__(self, df: DataFrame, id_col: str = "vec_id", vector: str = "x", metric: str = "l2"):
        self.metric = distance.known(metric)
        shaped = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).alias("x"))
        good, self.rejects = tables.checked(shaped, metric=metric)
        self.vectors = stage(good, "vectors")

    def index(self, kind: str = "nn_descent", parts: int = 1, **how) -> list[GraphIndex]:
        """An index of each of ``parts`` shards, split by hash of the id and built a shard a task."""
        v = self.vectors.withColumn("part", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int"))
        built = stage(builders.build(v, kind, self.metric, **how), "index")
        out = []
        for p in range(parts):
            own = built.where(F.col("index_id") == p)
            base = own.where("layer = 0").select("src", "dst", "dist")
            out.append(GraphIndex(base, v.where(F.col("part") == p).select("vec_id", "x"), self.metric, own.where("layer > 0").select("layer", "src", "dst", "dist")))
        return out


@dataclass
class GraphIndex:
    """A graph over vectors, with upper layers or none."""

    edges: DataFrame
    vectors: DataFrame
    metric: str = "l2"
    layers: DataFrame | None = None
    facts: dict = field(default_factory=dict)

    def entry(self) -> DataFrame:
        if "_entry" not in self.facts:
            self.facts["_entry"] = stage(search.medoids(self.vectors, self.metric), "entry")
        return self.facts["_entry"]

    def search(self, queries: DataFrame, k: int = 10, pool: int = 100) -> DataFrame:
        """``(q_id, index_id, rank, vec_id, dist, ndc, hops)`` for ``queries (vec_id, x)``."""
        if self.layers is not None and not self.layers.isEmpty():
            return tower.layered(self.edges, self.layers, self.vectors, queries, self.entry(), pool, k, self.metric)
        return search.resident(self.edges, self.vectors, queries, self.entry(), pool, k, self.metric)

    def stats(self) -> DataFrame:
        return quality.degrees(self.edges, self.vectors)

    def save(self, path: str) -> None:
        base = self.edges.select(F.lit(0).alias("layer"), "src", "dst", "dist")
        every = base if self.layers is None else base.unionByName(self.layers.select(F.col("layer").cast("int"), "src", "dst", "dist"))
        store.save(every, path, {"metric": self.metric}, self.entry())
        self.vectors.select("vec_id", "x").write.mode("overwrite").parquet(f"{path}/vectors")

    @classmethod
    def load(cls, spark: SparkSession, path: str, metric: str | None = None) -> GraphIndex:
        edges, meta = store.load(spark, path, metric)
        upper = edges.where("layer > 0").select("layer", "src", "dst", "dist")
        return cls(edges.where("layer = 0").select("src", "dst", "dist"), spark.read.parquet(f"{path}/vectors"), meta["metric"], None if upper.isEmpty() else upper)


def merge(indexes: Sequence[GraphIndex], k: int, **how) -> GraphIndex:
    """One index over the union; of a vector that several indexes hold, the copy of the last one stays."""
    if len(indexes) < 2:
        raise ValueError(f"a merge takes two indexes at least, not {len(indexes)}")
    metrics = {i.metric for i in indexes}
    if len(metrics) > 1:
        raise ValueError(f"indexes of one metric merge, not of {sorted(metrics)}")
    sizes = {r[0] for i in indexes for r in i.vectors.select(F.size("x")).limit(1).collect()}
    if len(sizes) > 1:
        raise ValueError(f"indexes of one dimension merge, not of {sorted(sizes)}")
    vectors = edges = None
    for p, one in enumerate(indexes):
        v, e = one.vectors.select("vec_id", "x", F.lit(p).alias("part")), one.edges.select("src", "dst", "dist", F.lit(p).alias("part"))
        vectors, edges = (v, e) if vectors is None else (vectors.unionByName(v), edges.unionByName(e))
    last = Window.partitionBy("vec_id").orderBy(F.desc("part"))
    kept = stage(vectors.withColumn("_r", F.row_number().over(last)).where("_r = 1").drop("_r"), "merge-vectors")
    for end in ("src", "dst"):
        edges = edges.join(kept.select(F.col("vec_id").alias(end), "part"), [end, "part"], "left_semi")
    got = fuse.merge(edges.select("src", "dst", "dist"), kept, k, metric=indexes[0].metric, **how)
    return GraphIndex(got.edges, kept.select("vec_id", "x"), indexes[0].metric, got.layers, got.facts)
