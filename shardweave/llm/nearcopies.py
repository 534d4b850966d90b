"""Near copies by SimHash and an exact check: texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more.

Equal sets are joined first, by a digest. The distinct ones are candidates of each other where their fingerprints differ in
``RADIUS`` bits or fewer, found by the vantage-point trees of :mod:`shardweave.llm.simhash`. Pairs near the threshold differ
in more bits than any tree can prune by (up to 17 of 64), so banded minima of the shingles' hashes hand out the other
candidates: what shares a band. The components of all candidates are blocks, so that each set travels once to its block. Of
two sets at the threshold, no band is shared with a chance of ``(1 - 0.8 ** ROWS) ** BANDS``, under 3e-7, and
less above it. Inside a block the rarest shingles of each set (as many as two similar sets can't all differ in) are looked
up and every pair found is compared in full, unless links before already joined it. A block larger than ``PER_BLOCK`` is
dealt out as pairs of its parts. Nothing is capped or sampled.

Defined cases: null, empty and blank texts are equal; texts shorter than a shingle hash as a whole; the rest is as in
:mod:`shardweave.llm.simhash`.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardweave.components import components
from shardweave.llm import simhash
from shardweave.staging import stage

SHINGLE = 5
SIMILARITY = 0.8
RADIUS = 2
SEED = 42
BANDS, ROWS = 50, 6
PER_BLOCK = 2048
#: Wanted texts that a broadcast may have (under 64 MB); beyond it the join shuffles.
BROADCAST_TEXTS = 2_000_000
BLOCK = 1 << 19
_FACTORS = np.random.default_rng(SEED).integers(1, 1 << 63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = np.random.default_rng(SEED + 1).integers(1, 1 << 63, (BANDS, ROWS), np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: bytes | None, shingle: int = SHINGLE) -> np.ndarray:
    """The sorted distinct shingle hashes of a UTF-8 text."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    if len(words) <= shingle:
        return np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[:-shingle]))
    hash_of = xxhash.xxh64_intdigest
    return np.unique(np.array([hash_of(line[a:b], SEED) for a, b in zip(starts.tolist(), (ends[shingle - 1 :] - 1).tolist(), strict=True)], np.uint64))


def digest(found: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(found.tobytes(), SEED) if len(found) else 0


def bands(found: np.ndarray) -> np.ndarray:
    """A key for each band of the set's minima; keys of different bands differ by their factors."""
    low = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    step = max(1, BLOCK // len(low))
    for at in range(0, len(found), step):
        low = np.minimum(low, (_FACTORS[:, None] * found[None, at : at + step]).min(axis=1))
    mixed = ((low.reshape(BANDS, ROWS) >> np.uint64(17)) ^ low.reshape(BANDS, ROWS)) * _MIX
    return np.bitwise_xor.reduce(mixed ^ (mixed >> np.uint64(29)), axis=1)


def digests(df: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE, banded: bool = False) -> DataFrame:
    """``(id, fp)`` with the digest of the shingles as a long; with ``banded`` also the text's hash, its fingerprint and the bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            known: dict[bytes, tuple[int, np.ndarray, int]] = {}
            rows = []
            for t in batch.column("text"):
                raw = t.as_py() or b""
                if raw not in known:
                    found = shingles(raw, shingle)
                    known[raw] = digest(found), bands(found).view(np.int64) if banded and len(found) else np.zeros(0, np.int64), simhash.majority(found) if banded else 0
                rows.append(known[raw])
            columns = {"id": batch.column("id"), "fp": pa.array(np.array([r[0] for r in rows], np.uint64).view(np.int64))}
            if banded:
                columns |= {"said": batch.column("said"), "mark": pa.array(np.array([r[2] for r in rows], np.uint64).view(np.int64)), "bands": pa.array([r[1] for r in rows], pa.list_(pa.int64()))}
            yield pa.RecordBatch.from_pydict(columns)

    slim = df.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(F.col(text)).alias("said"), F.col(text).cast("binary").alias("text"))
    return slim.mapInArrow(run, "id long, fp long" + (", said long, mark long, bands array<long>" if banded else ""))


def near(sets: list[np.ndarray], similarity: float = SIMILARITY) -> list[tuple[int, int]]:
    """A spanning forest of all pairs of ``sets`` that are similar."""
    sizes = np.array([len(s) for s in sets])
    kinds, at, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rank = np.empty(len(kinds), np.int64)
    rank[np.argsort(often, kind="stable")] = np.arange(len(kinds))
    ranked = np.split(rank[at], np.cumsum(sizes)[:-1])
    count = np.empty(len(kinds), np.int64)
    count[rank] = often
    label = list(range(len(sets)))

    def root(i: int) -> int:
        while label[i] != i:
            label[i] = label[label[i]]
            i = label[i]
        return i

    held: dict[int, list[int]] = defaultdict(list)
    mark = np.zeros(len(kinds), bool)
    out = []
    for i in np.argsort(sizes, kind="stable").tolist():
        own, size = np.sort(ranked[i]), int(sizes[i])
        if not size:
            continue
        first = own[: size - int(np.ceil(similarity * size - 1e-9)) + 1]
        first = first[count[first] > 1].tolist()
        mark[own] = True
        seen = set()
        for token in first:
            for j in held[token]:
                if j in seen:
                    continue
                seen.add(j)
                if sizes[j] < similarity * size - 1e-9 or root(i) == root(j):
                    continue
                both = int(mark[ranked[j]].sum())
                if both >= similarity * (size + int(sizes[j]) - both) - 1e-9:
                    out.append((i, j))
                    label[root(i)] = root(j)
            held[token].append(i)
        mark[own] = False
    return out


def links(df: DataFrame, distinct: DataFrame, text: str, shingle: int, similarity: float, per_block: int = PER_BLOCK) -> DataFrame:
    """A forest ``(a, b)`` over the digests whose components are those of all similar pairs."""
    keyed = distinct.select("fp", F.explode("bands").alias("key"))
    shared = keyed.groupBy("key").agg(F.min("fp").alias("low"), F.count("*").alias("n")).where("n > 1")
    drawn = keyed.join(shared, "key").where("fp <> low").select(F.col("fp").alias("a"), F.col("low").alias("b")).distinct()
    # Fingerprints in reach of each other, each by the smallest digest that has it.
    prints = stage(distinct.groupBy("mark").agg(F.min("fp").alias("low")), "near-prints")
    same = distinct.join(prints, "mark").where("fp <> low").select(F.col("fp").alias("a"), F.col("low").alias("b"))
    near_prints = simhash.links(prints.select(F.col("mark").alias("fp")), RADIUS)
    ends = near_prints.join(prints.select(F.col("mark").alias("a"), F.col("low").alias("x")), "a").join(prints.select(F.col("mark").alias("b"), F.col("low").alias("y")), "b")
    found = components(drawn.unionByName(same).unionByName(ends.select(F.col("x").alias("a"), F.col("y").alias("b"))))
    blocks = found.select(F.col("a").alias("fp"), F.col("b").alias("block")).unionByName(found.select(F.col("b").alias("fp"), F.col("b").alias("block")).distinct())
    parts = blocks.groupBy("block").agg(F.ceil(F.count("*") / per_block).cast("int").alias("parts"))
    wanted = stage(distinct.select("fp", "said").join(blocks, "fp").join(parts, "block"), "near-blocks")
    slim = df.select(F.xxhash64(F.col(text)).alias("said"), F.col(text).cast("binary").alias("text"))
    met = slim.join(F.broadcast(wanted) if wanted.count() <= BROADCAST_TEXTS else wanted, "said")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, rows, at = batch.column("fp").to_numpy().astype(np.int64).view(np.uint64), [], []
            for i, t in enumerate(batch.column("text")):
                own = shingles(t.as_py(), shingle)
                if digest(own) == int(fps[i]):
                    rows.append(own.view(np.int64))
                    at.append(i)
            some = batch.take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([some.column("fp"), some.column("block"), some.column("parts"), pa.array(rows, pa.list_(pa.int64()))], names=["fp", "block", "parts", "found"])

    # Exact copies of a text come once.
    once = met.select("fp", "block", "parts", "text").dropDuplicates(["fp"]).mapInArrow(sets, "fp long, block long, parts int, found array<long>")
    part = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
    dealt = once.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("block", F.least(part, "other").alias("i"), F.greatest(part, "other").alias("j"), "fp", "found")

    def join(group: pa.Table) -> pa.Table:
        fps = group.column("fp").to_numpy()
        pairs = near([np.asarray(x, np.int64).view(np.uint64) for x in group.column("found").to_numpy()], similarity)
        return pa.table({"a": pa.array([int(fps[a]) for a, _ in pairs], pa.int64()), "b": pa.array([int(fps[b]) for _, b in pairs], pa.int64())})

    return dealt.groupBy("block", "i", "j").applyInArrow(join, "a long, b long")


def keep_one(df: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """``df`` with one row of each class of near copies, chosen as in :func:`shardweave.llm.simhash.one_of`."""
    marked = stage(digests(df, id_col, text, shingle, True), "near")
    distinct = stage(marked.groupBy("fp").agg(F.min("id").alias("least"), F.min("said").alias("said"), F.min("mark").alias("mark"), F.first("bands").alias("bands")), "near-distinct")
    found = components(links(df, distinct, text, shingle, similarity))
    joined = found.select(F.col("a").alias("fp"), F.col("b").alias("root")).unionByName(found.select(F.col("b").alias("fp"), F.col("b").alias("root")).distinct())
    member = distinct.select("fp", "least").join(joined, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = member.groupBy("root").agg(F.min("least").alias("component_id"))
    return simhash.one_of(df, marked, member, least, lambda rows, key: digests(rows, key, text, shingle), id_col, text)
