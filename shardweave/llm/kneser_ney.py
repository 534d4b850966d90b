"""Toxicity by class-conditional Kneser-Ney models.

Two models, of toxic and of ordinary texts, give every word a probability behind the word before it. Each order takes an
absolute discount from its counts and hands what that frees to the order below: bigrams by the texts that hold them, words
by the contexts that they continue (their distinct predecessors), words' beginnings of six and of four bytes by the
contexts of their words, so that inflected and disguised forms speak as well. Below are shares that both classes have in
common: of a word in its beginning, of a beginning in the shorter one, and of the shortest. The discount of an order is
``n1 / (n1 + 2 n2)`` of its counts of counts, hence below one; counts under ``CUT`` are discounted in full. Both classes
hand the same weight down, the larger of theirs, and keep the rest for their own counts: expressions that both have rarely
or never seen get the same probability in both. Every order adds up to one (tests sum it up).

A text is scored by its length-normalised log ratio of the two models: over the whole text, over its most toxic window,
and, over the whole text again, of what exceeds ``STRONG`` at each word. A logistic curve, fitted on a bounded sample of
labelled rows that are each scored without their own counts, turns the three into a score.

Counts cover all labelled rows and come from one aggregation of bigrams. Words are 64-bit codes (six bytes as they are
and 16 bits of a checksum), contexts 32-bit checksums. Everything that reaches ``CUT`` is kept, in tables that grow with the
input. They are dealt by hash into shards of about ``PER_SHARD`` keys, each collected and broadcast on its own; where there
is more than one, a batch of texts asks one shard after the other for its keys.

Defined cases: null, empty and blank texts have no evidence and get the score of none; labels that are null or belong to
no row are not learnt from, and rows without an id have none; several labels of one id count its row once for each; with
one class only, scores are all 0.5; repeated rows and ties count as they come; an empty table gives an empty result; other
columns take no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.staging import drop, stage

#: Keys that one broadcast shard of the tables should hold, about 35 MB.
PER_SHARD = 1 << 20
#: Counts below it are discounted in full: what a few texts of the rarer class say is no evidence.
CUT = 5
WINDOW = 4
#: Labelled rows for the logistic curve, and how many labels a broadcast may have (under 64 MB).
CURVE_ROWS = 4000
BROADCAST_LABELS = 2_000_000
#: What one word can say, and from where on it counts as an expression of its own.
CLIP, STRONG = (-1.0, 6.0), 2.5
FEATURES = 3
WORD, SIX, FOUR, GRAM, CONTEXT, COUNTS = range(6)
_MARKS = bytes(c for c in range(33, 127) if not chr(c).isalnum())
_BLANKS = bytes.maketrans(_MARKS, b" " * len(_MARKS))
PACK = 32
LOW32 = (1 << 32) - 1
_BYTES = np.array([1 << (8 * (7 - i)) for i in range(6)], np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def tokens(text: bytes | None) -> tuple[np.ndarray, np.ndarray]:
    """The codes of the lower-case words of a text without punctuation, and the checksums of the words before them."""
    found = (text or b"").lower().translate(_BLANKS).split()
    n = len(found)
    check = np.fromiter(map(crc32, found), np.uint64, n)
    first = np.array(found, "S6").view(np.uint8).reshape(n, 6).astype(np.uint64) if n else np.zeros((0, 6), np.uint64)
    words = (first * _BYTES).sum(axis=1, dtype=np.uint64) | (check & np.uint64(0xFFFF))
    # The checksum of nothing, zero, stands before the first word.
    return words, np.concatenate((np.zeros(min(n, 1), np.uint64), check[:-1]))


def grams(words: np.ndarray, before: np.ndarray) -> np.ndarray:
    """Bigrams as 64-bit keys."""
    mixed = (words ^ (before * _ODD[0])) * _ODD[1]
    return mixed ^ (mixed >> np.uint64(29))


def find(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where ``keys`` are in a sorted table that isn't empty, and whether they are there."""
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return at, table[at] == keys


def held_out(id_col: str, parts: int, part: int) -> Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % parts == part


def labelled(docs: DataFrame, labels: DataFrame, id_col: str, label: str) -> DataFrame:
    """``docs`` joined to their labels without a shuffle of texts while the labels, counted first, fit a broadcast."""
    slim = labels.where(F.col(label).isNotNull()).select(F.col(id_col).alias("_id"), F.col(label).cast("int").alias("label"))
    if slim.count() <= BROADCAST_LABELS:
        slim = F.broadcast(slim)
    return docs.join(slim, docs[id_col] == F.col("_id")).drop("_id")


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bigrams ``(before, word)`` with the texts that hold them: toxic in the high half of a long, ordinary in the low half."""
    for batch in batches:
        held: list[list[tuple]] = [[], []]
        for text, label in zip(batch.column("text"), batch.column("label").to_pylist(), strict=True):
            words, before = tokens(text.as_py())
            # A text counts a bigram once, however often it repeats it.
            key, at = np.unique(grams(words, before), return_index=True)
            held[1 if label else 0].append((key, words[at], before[at]))
        for kind, many in enumerate(held):
            if many:
                key, words, before = (np.concatenate(x) for x in zip(*many, strict=True))
                _, at, n = np.unique(key, return_index=True, return_counts=True)
                columns = before[at].astype(np.uint32).view(np.int32), words[at].view(np.int64), n.astype(np.int64) << (PACK * kind)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["before", "word", "n"])


def both(packed: np.ndarray) -> np.ndarray:
    """The two classes' counts, ordinary first."""
    return np.stack((packed & LOW32, packed >> PACK))


def _sums(keys: np.ndarray, *counts: np.ndarray) -> tuple[np.ndarray, ...]:
    kinds, at = np.unique(keys, return_inverse=True)
    out = [np.zeros(len(kinds), np.int64) for _ in counts]
    for total, c in zip(out, counts, strict=True):
        np.add.at(total, at, c)
    return kinds, *out


def _fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of aggregated bigrams ``(kind, key, n, kept, sums)``: words with their contexts, contexts with all and with the kept
    counts, the bigrams that reach the cut, and counts of counts. ``kept`` of a word: it has such a bigram."""
    for batch in batches:
        before = batch.column("before").to_numpy().astype(np.int32).view(np.uint32).astype(np.uint64)
        word = batch.column("word").to_numpy().astype(np.int64).view(np.uint64)
        n = batch.column("n").to_numpy().astype(np.int64)
        counts = both(n)
        often = counts >= CUT
        some = often.any(axis=0)
        pack = lambda two: two[0].astype(np.int64) + (two[1].astype(np.int64) << PACK)
        words, types, held = _sums(word, pack(counts > 0), some.astype(np.int64))
        contexts, total, kept, sums = _sums(before, n, pack(often), pack(np.where(often, counts, 0)))
        few = np.array([(counts == r).sum() for r in (1, 2)], np.int64)
        none = lambda k: np.zeros(k, np.int64)
        rows = [
            (WORD, words, types, held, none(len(words))), (CONTEXT, contexts, total, kept, sums),
            (GRAM, grams(word[some], before[some]), n[some], none(int(some.sum())), none(int(some.sum()))), (COUNTS, np.array([1, 2], np.uint64), few, none(2), none(2)),
        ]
        kind = np.concatenate([np.full(len(r[1]), r[0], np.int8) for r in rows])
        key = np.concatenate([r[1] for r in rows]).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(key), *(pa.array(np.concatenate([r[i] for r in rows])) for i in (2, 3, 4))], names=["kind", "key", "n", "kept", "sums"])


class Shards:
    """The broadcast shards of the tables; each has the columns ``kind, key, a, b, c``."""

    def __init__(self, held: list, totals: dict):
        self.held, self.totals = held, totals
        self.whole: Model | None = None

    def model(self, texts: list[tuple[np.ndarray, np.ndarray]]) -> Model:
        """The model for texts of these tokens: of a single shard all of it, else what the texts ask for."""
        if len(self.held) == 1:
            self.whole = self.whole or Model(self.held[0].value, self.totals)
            return self.whole
        words = np.unique(np.concatenate([t[0] for t in texts] or [np.zeros(0, np.uint64)]))
        ask = {WORD: words, SIX: np.unique(words >> np.uint64(16)), FOUR: np.unique(words >> np.uint64(32))}
        ask[GRAM] = np.unique(np.concatenate([grams(*t) for t in texts] or [words]))
        ask[CONTEXT] = np.unique(np.concatenate([t[1] for t in texts] or [words]))
        got = []
        for one in self.held:
            rows = one.value
            wanted = np.zeros(len(rows["key"]), bool)
            for kind, keys in ask.items():
                lo, hi = np.searchsorted(rows["kind"], [kind, kind + 1])
                wanted[lo:hi] = np.isin(rows["key"][lo:hi], keys)
            got.append({k: v[wanted] for k, v in rows.items()})
            one.__dict__.pop("_value", None)
            del rows
        return Model({k: np.concatenate([g[k] for g in got]) for k in got[0]}, self.totals)


class Model:
    """The two class models in sorted tables. ``a`` and ``b`` are the classes' counts (of contexts: what is left of them after
    the discount), ``c`` the pooled count of what is kept of the order above (of contexts: the weight handed down)."""

    def __init__(self, rows: dict[str, np.ndarray], totals: dict):
        self.table = {}
        for kind in range(5):
            own = np.flatnonzero(rows["kind"] == kind)
            own = own[np.argsort(rows["key"][own])]
            # A last key that nothing has: no table is empty.
            key = np.append(rows["key"][own], np.uint64(2**64 - 1))
            self.table[kind] = key, np.stack([np.append(rows[c][own], 0.0) for c in "ab"]), np.append(rows["c"][own], 0.0)
        self.totals = totals

    def less(self, kind: int, n: np.ndarray) -> np.ndarray:
        return np.where(n >= CUT, n - self.totals["discount"][kind], 0.0)

    def probabilities(self, words: np.ndarray, before: np.ndarray, own: int | None = None) -> np.ndarray:
        """``(2, n)``: each word's probability behind the word before it, ordinary and toxic. ``own``: without this text's
        counts in its class. What the tables lack counts as one event, the rest, of its beginning."""
        t = self.totals
        key = {WORD: words, SIX: words >> np.uint64(16), FOUR: words >> np.uint64(32), GRAM: grams(words, before), CONTEXT: before}
        place = {kind: find(self.table[kind][0], k) for kind, k in key.items()}
        count = {kind: np.where(place[kind][1], self.table[kind][1][:, place[kind][0]], 0.0) for kind in key}
        extra = {kind: np.where(place[kind][1], self.table[kind][2][place[kind][0]], 0.0) for kind in key}
        # Shares that both classes have in common: of the shortest beginning, of a longer one in it, of a word in that one.
        pooled = {kind: count[kind].sum(axis=0) for kind in (WORD, SIX, FOUR)}
        base = np.where(place[FOUR][1], pooled[FOUR], t["all"] - t["kept"] + 1) / (t["all"] + 1)
        six = np.where(place[SIX][1], pooled[SIX], pooled[FOUR] - extra[FOUR] + 1) / (pooled[FOUR] + 1)
        one = np.where(place[WORD][1], pooled[WORD], pooled[SIX] - extra[SIX] + 1) / (pooled[SIX] + 1)
        mine = {}
        if own is not None:
            # This text's own distinct bigrams, as contexts of words and of beginnings.
            _, at = np.unique(key[GRAM], return_index=True)
            for kind in (WORD, SIX, FOUR):
                kinds, times = np.unique(key[kind][at], return_counts=True)
                mine[kind] = times[np.searchsorted(kinds, key[kind])]
            mine[GRAM] = 1
        # A context hands all down unless both classes kept something of it.
        down = np.where(place[CONTEXT][1], extra[CONTEXT], 1.0)
        out = []
        for c in range(2):
            n = {kind: np.maximum(count[kind][c] - mine[kind], 0) if own == c else count[kind][c] for kind in (WORD, SIX, FOUR, GRAM)}
            p = base
            for kind, share in ((FOUR, None), (SIX, six), (WORD, one)):
                lower = p if share is None else share * p
                p = (1 - t["down"][kind]) * self.less(kind, n[kind]) / t["left"][kind][c] + t["down"][kind] * lower
                # In an event of rests the order above has nothing to tell apart.
            bigram = np.where(down < 1, self.less(GRAM, n[GRAM]) / np.maximum(count[CONTEXT][c], 1e-300), 0.0)
            out.append((1 - down) * bigram + down * p)
        return np.stack(out)

    def evidence(self, words: np.ndarray, before: np.ndarray, own: int | None = None) -> np.ndarray:
        """Each word's log ratio, toxic over ordinary."""
        ordinary, toxic = self.probabilities(words, before, own)
        return np.clip(np.log(toxic / ordinary), *CLIP)

    def features(self, found: tuple[np.ndarray, np.ndarray], own: int | None = None) -> tuple[float, ...]:
        """The log ratio a word of a text, of its most toxic window, and of what exceeds ``STRONG``."""
        if not len(found[0]):
            return (0.0,) * FEATURES
        ratio = self.evidence(*found, own)
        run = np.concatenate(([0.0], np.cumsum(ratio)))
        width = min(WINDOW, len(ratio))
        return float(ratio.mean()), float((run[width:] - run[:-width]).max() / width), float(10 * np.maximum(ratio - STRONG, 0).mean())


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Weights of a ridge logistic regression by Newton steps; the first is the constant."""
    x = np.column_stack((np.ones(len(x)), x))
    w = np.zeros(x.shape[1])
    keep = ridge * np.eye(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p) + 1e-9)[:, None]) + keep, x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def discount(n1: float, n2: float) -> float:
    """The absolute discount of counts of counts; a half where there are none."""
    return n1 / (n1 + 2 * n2) if n1 else 0.5


def fit(rows: DataFrame, text: str = "text") -> Shards | None:
    """The models from rows with a ``label``; None where a class has no row with a word."""
    given = rows.select(F.col(text).cast("binary").alias("text"), "label")
    found = given.mapInArrow(_count, "before int, word long, n long").groupBy("before", "word").agg(F.sum("n").alias("n"))
    folded = found.mapInArrow(_fold, "kind byte, key long, n long, kept long, sums long")
    parts = stage(folded.groupBy("kind", "key").agg(*[F.sum(c).alias(c) for c in ("n", "kept", "sums")]), "kneser-ney")
    low, high = (lambda c: F.col(c).bitwiseAND(LOW32)), (lambda c: F.shiftright(c, PACK))
    words = parts.where(F.col("kind") == WORD).select("key", low("n").alias("a"), high("n").alias("b"), (F.col("kept") > 0).alias("kept"))
    reaches = (F.col("a") >= CUT) | (F.col("b") >= CUT) | F.col("kept")
    pool = F.col("a") + F.col("b")
    sums = [F.sum("a").alias("a"), F.sum("b").alias("b")]
    above = lambda kept: F.sum(F.when(kept, pool).otherwise(0)).alias("c")
    # A beginning is kept where its own counts reach the cut or a word of it is kept.
    six = stage(words.groupBy(F.shiftrightunsigned("key", 16).alias("key")).agg(*sums, F.max(reaches).alias("kept"), above(reaches)), "kneser-ney-six")
    four = stage(six.groupBy(F.shiftrightunsigned("key", 16).alias("key")).agg(*sums, F.max(reaches).alias("kept"), above(reaches)), "kneser-ney-four")
    totals: dict = {"discount": {}, "down": {}, "left": {}}
    for kind, table in ((WORD, words), (SIX, six), (FOUR, four)):
        facts = table.agg(
            *[F.sum(F.col(c)).alias(f"n_{c}") for c in "ab"], *[F.sum((F.col("a") == r).cast("long") + (F.col("b") == r).cast("long")).alias(f"of_{r}") for r in (1, 2)],
            *[F.sum(F.when(F.col(c) >= CUT, F.col(c)).otherwise(0)).alias(f"s_{c}") for c in "ab"], *[F.sum((F.col(c) >= CUT).cast("long")).alias(f"k_{c}") for c in "ab"],
            F.sum(F.when(reaches, pool).otherwise(0)).alias("kept"),
        ).first()
        if not facts["n_a"] or not facts["n_b"]:
            return None
        d = totals["discount"][kind] = discount(facts["of_1"], facts["of_2"])
        left = [float(facts[f"s_{c}"] - d * facts[f"k_{c}"]) for c in "ab"]
        totals["down"][kind] = max(1 - x / facts[f"n_{c}"] for x, c in zip(left, "ab", strict=True))
        totals["left"][kind] = [max(x, 1e-300) for x in left]
        totals["all"], totals["kept"] = float(facts["n_a"] + facts["n_b"]), float(facts["kept"])
    few = {r["key"]: r["n"] for r in parts.where(F.col("kind") == COUNTS).collect()}  # two rows
    d = totals["discount"][GRAM] = discount(few.get(1, 0), few.get(2, 0))
    shape = lambda df, kind, c: df.select(F.lit(kind).cast("byte").alias("kind"), "key", *[F.col(x).cast("double").alias(x) for x in "ab"], c.cast("double").alias("c"))
    rest = lambda half: half("sums") - d * half("kept")
    contexts = parts.where((F.col("kind") == CONTEXT) & (low("kept") > 0) & (high("kept") > 0)).select("key", rest(low).alias("a"), rest(high).alias("b"), low("n").alias("m"), high("n").alias("k"))
    tables = shape(words.where(reaches), WORD, F.lit(0.0)).unionByName(shape(six.where(reaches), SIX, F.col("c"))).unionByName(shape(four.where(reaches), FOUR, F.col("c")))
    tables = tables.unionByName(shape(contexts, CONTEXT, F.greatest(1 - F.col("a") / F.col("m"), 1 - F.col("b") / F.col("k"))))
    tables = tables.unionByName(shape(parts.where(F.col("kind") == GRAM).select("key", low("n").alias("a"), high("n").alias("b")), GRAM, F.lit(0.0)))
    tables = stage(tables, "kneser-ney-tables")
    count = max(1, -(-tables.count() // PER_SHARD))
    if count > 1:
        dealt = stage(tables.withColumn("shard", F.pmod(F.xxhash64("kind", "key"), F.lit(count)).cast("int")).repartition(count, "shard"), "kneser-ney-shards", ["shard"])
        drop(tables)
        tables = dealt
    held = []
    for at in range(count):
        got = (tables.where(F.col("shard") == at) if count > 1 else tables).select("kind", "key", "a", "b", "c").toArrow()
        one = {k: got.column(k).to_numpy() for k in got.column_names}
        one["key"] = one["key"].astype(np.int64).view(np.uint64)
        order = np.lexsort((one["key"], one["kind"]))
        held.append(rows.sparkSession.sparkContext.broadcast({k: v[order] for k, v in one.items()}))
    for used in (parts, six, four, tables):
        drop(used)
    return Shards(held, totals)


def score(docs: DataFrame, labels: DataFrame, train: Column, id_col: str = "doc_id", text: str = "text", label: str = "toxic", curve_rows: int = CURVE_ROWS) -> DataFrame:
    """``(id, score)`` of every row of ``docs``; labels are learnt from where ``train`` holds."""
    own = labels.where(train)
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("binary").alias("text"))
    named = docs.select(F.col(id_col), F.col(text).alias("text"))
    model = fit(labelled(named, own, id_col, label))
    weights = np.zeros(1 + FEATURES)
    held, totals = (model.held, model.totals) if model else ([], {})
    if model is not None:
        few = stage(own.where(F.col(label).isNotNull()).orderBy(F.xxhash64(id_col), id_col).limit(curve_rows), "curve-rows")
        some = labelled(named, few, id_col, label).select(F.col("text").cast("binary").alias("text"), "label")

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tables = Shards(held, totals)
            for batch in batches:
                y = batch.column("label").to_pylist()
                said = [tokens(t.as_py()) for t in batch.column("text")]
                own = tables.model(said)
                x = [own.features(t, 1 if c else 0) for t, c in zip(said, y, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), pa.array(y, pa.int32())], names=["x", "y"])

        got = some.mapInArrow(measure, "x array<double>, y int").toPandas()
        drop(few)
        rows = np.array([(*x, y) for x, y in zip(got["x"], got["y"], strict=True)]).reshape(-1, FEATURES + 1)
        rows = rows[np.lexsort(rows.T)]
        if len(np.unique(rows[:, -1])) == 2:
            weights = logistic(rows[:, :-1], (rows[:, -1] > 0).astype(float))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = Shards(held, totals) if held else None
        for batch in batches:
            said = [tokens(t.as_py()) for t in batch.column("text")] if tables else []
            own = tables.model(said) if tables else None
            found = np.array([own.features(t) for t in said] if own else [(0.0,) * FEATURES] * batch.num_rows).reshape(-1, FEATURES)
            z = weights[0] + found @ weights[1:]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(1 / (1 + np.exp(-np.clip(z, -30, 30))))], names=["id", "score"])

    return slim.mapInArrow(judge, "id long, score double")
