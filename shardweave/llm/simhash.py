"""SimHash near-duplicates: exact pairs of fingerprints by vantage-point trees, and their connected classes.

Fingerprints are majority bits of the XXH64 hashes of word shingles. Equal fingerprints are joined first; a tree over the
distinct ones is fitted on a sample and cuts them into shards by Hamming distance to vantage points. Every
fingerprint lives in one shard and asks in each further shard that its ball overlaps: where its distance to a vantage
point is within the radius of the boundary, both sides are visited, by the triangle inequality. Inside a shard a finer
tree prunes in the same way, over all askers at once, down to small leaves that are compared in full. Shards send a
spanning forest of their links, not all pairs, and the classes are the components of the forests.

Defined cases: null, empty and blank texts have fingerprint zero and are linked as any other; texts shorter than a
shingle hash as a whole; equal rows and ties share a class; null ids are never a class's smallest unless all are null;
an empty table gives an empty result; other columns are kept by ``keep_one``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardweave.components import components
from shardweave.llm.textcols import unused
from shardweave.staging import stage

RADIUS = 2
SHINGLE = 3
SEED = 42
#: Fingerprints that the upper tree is fitted on: so many, or so many a shard where that is more (0.2 % of the distinct
#: ones, 8 bytes each); and how many fingerprints one shard should hold.
SAMPLE, SAMPLE_PER_SHARD = 8192, 4
PER_SHARD = 2048
LEAF = 256
BLOCK = 1 << 22


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    """The fingerprint of a UTF-8 text as an unsigned number. ``bytes`` lower and split know ASCII only, as wanted."""
    words = text.lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        hashes = [xxhash.xxh64_intdigest(line, SEED)]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = np.concatenate(([0], ends[:-shingle]))
        hash_of = xxhash.xxh64_intdigest
        hashes = [hash_of(line[a:b], SEED) for a, b in zip(starts.tolist(), (ends[shingle - 1 :] - 1).tolist(), strict=True)]
    return majority(hashes)


def majority(hashes: list[int] | np.ndarray) -> int:
    """The bits that more than half of the hashes have; zero for none."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        h = np.array(hashes[at : at + (1 << 16)], np.uint64)
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * counts > len(hashes)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``(id, fp)`` with the fingerprint as a long; equal texts inside a batch are hashed once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            known: dict[bytes, int] = {}
            out = np.empty(batch.num_rows, np.uint64)
            for i, t in enumerate(batch.column("text")):
                raw = t.as_py() or b""
                if raw not in known:
                    known[raw] = fingerprint(raw, shingle)
                out[i] = known[raw]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(out.view(np.int64))], names=["id", "fp"])

    slim = df.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("binary").alias("text"))
    return slim.mapInArrow(run, "id long, fp long")


# --- the tree that cuts fingerprints into shards ---


def plant(sample: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray]:
    """The nodes' vantage points, and rows ``(boundary, near, far)``; a child below zero is the shard ``-1 - child``. The root comes first."""
    nodes: list[tuple[int, int, int, int]] = []
    leaves = [0]

    def leaf() -> int:
        leaves[0] += 1
        return -leaves[0]

    def grow(points: np.ndarray, want: int) -> int:
        if want <= 1 or len(points) < 2:
            return leaf()
        tried = points[:: max(1, len(points) // 8)][:8]
        spread = [np.bitwise_count(points ^ v).astype(np.int64).std() for v in tried]
        vantage = tried[int(np.argmax(spread))]
        far = np.bitwise_count(points ^ vantage).astype(np.int64)
        boundary = int(np.median(far))
        near = far <= boundary
        if near.all():
            near = far < boundary
            boundary -= 1
        if not near.any() or near.all():
            return leaf()
        at = len(nodes)
        nodes.append((0, 0, 0, 0))
        own = max(1, round(want * near.mean()))
        left = grow(points[near], own)
        nodes[at] = (int(vantage), boundary, left, grow(points[~near], max(1, want - own)))
        return at

    grow(sample, shards)
    return np.array([n[0] for n in nodes], np.uint64), np.array([n[1:] for n in nodes], np.int64).reshape(-1, 3)


def route(points: np.ndarray, nodes: tuple[np.ndarray, np.ndarray], radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(index of the point, shard, whether it lives there)`` of every visit."""
    if not len(nodes[0]):
        return np.arange(len(points)), np.zeros(len(points), np.int64), np.ones(len(points), bool)
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    todo = [(0, np.arange(len(points)), np.ones(len(points), bool))]
    while todo:
        at, idx, home = todo.pop()
        boundary, near, far = nodes[1][at].tolist()
        away = np.bitwise_count(points[idx] ^ nodes[0][at]).astype(np.int64)
        for child, visit, lives in ((near, away <= boundary + radius, away <= boundary), (far, away > boundary - radius, away > boundary)):
            i, h = idx[visit], (home & lives)[visit]
            if len(i) == 0:
                continue
            if child < 0:
                out.append((i, np.full(len(i), -1 - child), h))
            else:
                todo.append((child, i, h))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


# --- links inside one shard ---


def merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the classes of all pairs, in place; a label is the index of the smallest member known."""
    while len(a):
        la, lb = label[a], label[b]
        differ = la != lb
        if not differ.any():
            return
        a, b, la, lb = a[differ], b[differ], la[differ], lb[differ]
        np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up


def link(points: np.ndarray, home: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """For each point the index of the smallest one of its class, by links between any point and points at home."""
    order = np.argsort(points, kind="stable")
    points, home = points[order], home[order]
    label = np.arange(len(points))
    todo = [(np.flatnonzero(home), np.arange(len(points)))]
    while todo:
        own, ask = todo.pop()
        if len(own) == 0 or len(ask) == 0:
            continue
        near = None
        if len(own) > LEAF:
            vantage = points[own[len(own) // 2]]
            away = np.bitwise_count(points[own] ^ vantage).astype(np.int64)
            boundary = int(np.median(away))
            near = away <= boundary
        if near is None or near.all():
            step = max(1, BLOCK // len(own))
            for at in range(0, len(ask), step):
                some = ask[at : at + step]
                r, c = np.nonzero(np.bitwise_count(points[some][:, None] ^ points[own][None, :]) <= radius)
                merge(label, some[r], own[c])
            continue
        far = np.bitwise_count(points[ask] ^ vantage).astype(np.int64)
        todo.append((own[near], ask[far <= boundary + radius]))
        todo.append((own[~near], ask[far > boundary - radius]))
    out = np.empty(len(points), np.int64)
    out[order] = order[label]
    return out


def links(distinct: DataFrame, radius: int = RADIUS, per_shard: int = PER_SHARD, sample: int = SAMPLE) -> DataFrame:
    """A forest ``(a, b)`` over the distinct fingerprints ``fp`` whose components are those of all pairs in reach."""
    n = distinct.count()
    shards = max(1, -(-n // per_shard))
    fitted = np.zeros(0, np.uint64)
    if shards > 1:
        # The smallest hashes.
        rows = distinct.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(max(sample, SAMPLE_PER_SHARD * shards)).toArrow()
        fitted = rows.column("fp").to_numpy().astype(np.int64).view(np.uint64)
    held = distinct.sparkSession.sparkContext.broadcast(plant(fitted, shards if len(fitted) else 1))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes = held.value
        for batch in batches:
            points = batch.column("fp").to_numpy().astype(np.int64).view(np.uint64)
            i, shard, home = route(points, nodes, radius)
            yield pa.RecordBatch.from_arrays([pa.array(shard.astype(np.int32)), pa.array(points[i].view(np.int64)), pa.array(home)], names=["shard", "fp", "home"])

    def join(group: pa.Table) -> pa.Table:
        points = group.column("fp").to_numpy().astype(np.int64).view(np.uint64)
        low = points[link(points, group.column("home").to_numpy(), radius)]
        kept = low != points
        return pa.table({"a": points[kept].view(np.int64), "b": low[kept].view(np.int64)})

    return distinct.select("fp").mapInArrow(send, "shard int, fp long, home boolean").groupBy("shard").applyInArrow(join, "a long, b long")


def _classed(df: DataFrame, id_col: str, text: str, shingle: int, radius: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(id, fp)`` of the rows, ``(fp, least, root)`` of the distinct fingerprints, ``(root, component_id)`` of the classes."""
    marked = stage(fingerprints(df, id_col, text, shingle), "simhash")
    distinct = stage(marked.groupBy("fp").agg(F.min("id").alias("least")), "simhash-distinct")
    found = components(links(distinct, radius))
    # Fingerprints of classes of their own need no class table: their smallest id is at hand.
    joined = found.select(F.col("a").alias("fp"), F.col("b").alias("root")).unionByName(found.select(F.col("b").alias("fp"), F.col("b").alias("root")).distinct())
    member = distinct.join(joined, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    return marked, member, member.groupBy("root").agg(F.min("least").alias("component_id"))


def classes(df: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """``(id, fp, component_id)``: the smallest id that links lead to."""
    marked, member, least = _classed(df, id_col, text, shingle, radius)
    by_print = member.join(least, "root").select(F.col("fp").alias("_fp"), "component_id")
    return marked.join(by_print, marked["fp"] == by_print["_fp"]).drop("_fp")


def hexadecimal(fp: str = "fp"):
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def keep_one(df: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """``df`` with one row of each class, as :func:`one_of` chooses it."""
    marked, member, least = _classed(df, id_col, text, shingle, radius)
    return one_of(df, marked, member, least, lambda rows, key: fingerprints(rows, key, text, shingle), id_col, text)


def one_of(df: DataFrame, marked: DataFrame, member: DataFrame, least: DataFrame, marks: Callable[[DataFrame, str], DataFrame], id_col: str, text: str) -> DataFrame:
    """``df`` with one row of each class, that of the smallest id. ``marked`` holds rows ``(id, fp)``.

    Where rows of one id are in several classes, they are told apart by a digest of their texts, whose fingerprints
    ``marks`` gives as ``(id, fp)`` by the named key; of such rows, and of rows without an id, a class keeps the one with
    the smallest digest.
    """
    digest, of, root = unused(df, "_digest", "_of", "_root")
    said = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    own = F.col(id_col).cast("long")
    # Only ids with several fingerprints need their classes; a join of all rows would send a group of copies to one task.
    several = marked.where("id is not null").groupBy("id").agg(F.min("fp").alias("low"), F.max("fp").alias("high")).where("low <> high").select("id")
    placed = marked.join(several, "id", "left_semi").select("id", "fp").distinct().join(member.select("fp", "root"), "fp")
    mixed = stage(placed.groupBy("id").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select(F.col("id").alias("component_id")), "mixed-ids")
    first = least.where("component_id is not null")
    # Join and deduplication share the partitioning by id.
    plain = first.join(mixed, "component_id", "left_anti").select(F.col("component_id").alias(of))
    named = df.join(plain, own == F.col(of), "left_semi").dropDuplicates([id_col])
    twins = df.join(mixed.select(F.col("component_id").alias(of)), own == F.col(of), "left_semi").withColumn(digest, said)
    blank = df.where(F.col(id_col).isNull()).withColumn(digest, said)
    for rows, classes_ in ((twins, first.join(mixed, "component_id", "left_semi")), (blank, least.where("component_id is null"))):
        prints = marks(rows, digest).distinct().join(member.select("fp", "root"), "fp").select(F.col("id").alias(of), F.col("root").alias(root))
        met = rows.join(prints, F.col(digest) == F.col(of)).drop(of)
        wanted = classes_.select(F.col("root").alias(of), F.col("component_id").alias(f"{of}id"))
        kept = met.join(wanted, (F.col(root) == F.col(of)) & own.eqNullSafe(F.col(f"{of}id")), "left_semi")
        low = kept.groupBy(F.col(root).alias(of)).agg(F.min(digest).alias(f"{of}id"))
        kept = kept.join(low, (F.col(root) == F.col(of)) & (F.col(digest) == F.col(f"{of}id")), "left_semi")
        named = named.unionByName(kept.dropDuplicates([root]).drop(root, digest))
    return named
