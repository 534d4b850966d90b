"""SentencePiece encoding and decoding over a relational lattice.

Text becomes words: runs of the space mark, then other characters up to the next space or line end. No piece reaches
over such a border (checked when pieces are loaded), so words are encoded apart. :func:`lattice` is the relational form:
substrings of bounded length are exploded from distinct words, equi-joined to the piece table, grouped by word, and a
Spark higher-order ``aggregate`` folds the Viterbi recursion over the edges. :func:`encode` lets it encode the corpus's
most frequent words, a dictionary of bounded size that is broadcast; rarer words, whose number grows with the input, go
through the same lattice in the task that reads them. So texts are never shuffled.

Paths maximise the sum of piece scores; of equal paths, the one with the longer last piece wins at each place. Characters
without a piece become byte pieces. Decoding joins the pieces' bytes; a text comes back exactly, but for the space mark
itself (U+2581), which comes back as a space.

Defined cases: a null text has null ids, an empty one no ids, and both decode to themselves; ill-formed ids are an error;
repeated rows encode alike; an empty table gives an empty result; other columns of the input take no part.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.staging import drop, stage

SPACE = "▁"
WORD = rf"{SPACE}*[^{SPACE}\n]+|\n|{SPACE}+"
#: Bounds: words in the broadcast dictionary, pieces of a model.
DICTIONARY, PIECES = 200_000, 1_000_000
#: Rarer words that a task keeps at a time.
KEPT = 400_000
PENALTY = 10.0
#: Back pointers of a word are kept in blocks, so that a very long word is not copied at every step.
BLOCK = 256
#: Characters of text that one output batch holds the ids of.
SLICE = 4 << 20


class Pieces:
    """A piece table: score and id by piece, the bytes of each id, and the ids of bytes."""

    def __init__(self, score: dict[str, tuple[float, int]], raw: dict[int, bytes], byte_ids: dict[int, int], unknown: int):
        self.score, self.raw, self.byte_ids, self.unknown = score, raw, byte_ids, unknown
        self.longest = max(map(len, score), default=1)
        #: Score, id and whether a longer piece goes on, for every piece and (id -1) every other beginning of one.
        begun = {p[:i] for p in score for i in range(1, len(p))}
        self.step = {p: (*score.get(p, (0.0, -1)), p in begun) for p in begun | score.keys()}
        self.floor = min((s for s, _ in score.values()), default=0.0) - PENALTY

    def spell(self, char: str) -> tuple[int, ...]:
        return tuple(self.byte_ids.get(b, self.unknown) for b in char.encode())


def load(path: str) -> Pieces:
    """Pieces of a model file; read on the driver, bounded by :data:`PIECES`."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.get_piece_size()
    if n > PIECES:
        raise ValueError(f"{n} pieces are more than {PIECES}")
    score, raw, byte_ids = {}, {}, {}
    for i in range(n):
        piece = model.id_to_piece(i)
        if model.is_byte(i):
            byte_ids[int(piece[3:5], 16)] = i
            raw[i] = bytes([int(piece[3:5], 16)])
        elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
            if "\n" in piece or SPACE in piece.lstrip(SPACE):
                raise ValueError(f"piece {piece!r} reaches over the end of a word")
            score[piece] = (model.get_score(i), i)
            raw[i] = piece.replace(SPACE, " ").encode()
    return Pieces(score, raw, byte_ids, model.unk_id())


def marked(text: Column) -> Column:
    """A text with a leading space, all spaces as marks; the empty text stays empty."""
    return F.when(text == "", text).otherwise(F.concat(F.lit(SPACE), F.replace(text, F.lit(" "), F.lit(SPACE))))


# --- the relational lattice ---


def lattice(words: DataFrame, pieces: Pieces, word: str = "word") -> DataFrame:
    """``(word, ids)`` for distinct words.

    If ``words`` comes from a grouping by word, its partitioning serves the grouping of the edges: no further shuffle.
    """
    spark = words.sparkSession
    known = [(p, s, [i]) for p, (s, i) in pieces.score.items()]
    table = F.broadcast(spark.createDataFrame(known, "piece string, score double, ids array<int>"))
    n = F.length(word)
    at = words.select(word, F.explode(F.sequence(F.lit(0), n - 1)).alias("start"))
    reach = F.least(F.lit(pieces.longest), n - F.col("start"))
    spans = at.select(word, "start", F.explode(F.sequence(F.lit(1), reach)).alias("len"))
    spans = spans.withColumn("piece", F.substring(F.col(word), F.col("start") + 1, F.col("len")))
    met = spans.join(table, "piece", "left").where(F.col("ids").isNotNull() | (F.col("len") == 1))
    codes = F.from_json(F.lit(str([pieces.byte_ids.get(b, pieces.unknown) for b in range(256)])), "array<int>")
    hexes = F.regexp_extract_all(F.hex(F.encode("piece", "utf-8")), F.lit(".."), F.lit(0))
    spelt = F.transform(hexes, lambda h: F.get(codes, F.conv(h, 16, 10).cast("int")))
    edge = F.struct(
        (F.col("start") + F.col("len")).alias("end"), "start", F.coalesce("score", F.lit(pieces.floor)).alias("score"), F.coalesce("ids", spelt).alias("ids")
    )
    edges = met.groupBy(word).agg(F.array_sort(F.collect_list(edge)).alias("edges"))
    return edges.select(word, viterbi(F.col("edges"), pieces.longest).alias("ids"))


def viterbi(edges: Column, longest: int) -> Column:
    """The ids of the best path through edges in order of end and start.

    The state keeps the scores of the last ``longest + 1`` places only, and the best edge into each place in blocks.
    """
    links = "array<struct<start:int,ids:array<int>>>"
    start = F.struct(
        F.array(F.lit(0.0)).alias("tail"), F.lit(0).alias("end"), F.lit(0.0).alias("best"), F.lit(0).alias("from"), F.array().cast("array<int>").alias("ids"),
        F.array().cast(links).alias("block"), F.array().cast(f"array<{links}>").alias("blocks"),
    )

    def close(s: Column) -> Column:
        """The state once no further edge ends at its place."""
        block = F.concat(s.block, F.array(F.struct(s["from"].cast("int").alias("start"), s.ids.alias("ids"))))
        full = F.size(block) >= BLOCK
        tail = F.concat(s.tail, F.array(s.best))
        return F.struct(
            F.slice(tail, -F.least(F.size(tail), F.lit(longest + 1)), F.lit(longest + 1)).alias("tail"), s.end.alias("end"), s.best.alias("best"), s["from"].alias("from"), s.ids.alias("ids"),
            F.when(full, F.array().cast(links)).otherwise(block).alias("block"), F.when(full, F.concat(s.blocks, F.array(block))).otherwise(s.blocks).alias("blocks"),
        )

    def take(s: Column, e: Column) -> Column:
        def weigh(now: Column) -> Column:
            # The tail ends with the place before the one that this edge enters.
            total = F.get(now.tail, F.size(now.tail) - (e.end - e.start)) + e.score
            better = (now.end < e.end) | (total > now.best)
            pick = lambda new, old: F.when(better, new).otherwise(old)
            return F.struct(
                now.tail.alias("tail"), e.end.alias("end"), pick(total, now.best).alias("best"), pick(e.start, now["from"]).alias("from"), pick(e.ids, now.ids).alias("ids"),
                now.block.alias("block"), now.blocks.alias("blocks"),
            )

        opened = F.when((s.end > 0) & (e.end > s.end), close(s)).otherwise(s)
        return F.get(F.transform(F.array(opened), weigh), F.lit(0))

    def back(s: Column) -> Column:
        done = F.get(F.transform(F.array(close(s)), lambda x: F.concat(F.flatten(x.blocks), x.block)), F.lit(0))

        def path(places: Column) -> Column:
            begin = F.struct(F.size(places).alias("at"), F.array().cast("array<int>").alias("ids"))
            steps = F.reverse(F.transform(places, lambda p, i: F.struct((i + 1).alias("end"), p.start.alias("start"), p.ids.alias("ids"))))
            walk = lambda a, p: F.when(p.end == a.at, F.struct(p.start.alias("at"), F.concat(p.ids, a.ids).alias("ids"))).otherwise(a)
            return F.aggregate(steps, begin, walk).ids

        return F.get(F.transform(F.array(done), path), F.lit(0))

    return F.aggregate(edges, start, take, back)


# --- the same lattice for the words of one task ---


def word_ids(word: str, pieces: Pieces) -> tuple[int, ...]:
    """The ids of the best path through one word."""
    n, step, longest, floor = len(word), pieces.step.get, pieces.longest, pieces.floor
    best, came, ids = [float("-inf")] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
    best[0] = 0.0
    for start in range(n):
        base, end, stop = best[start], start + 1, min(n, start + longest)
        while True:
            score, at, more = step(word[start:end], (0.0, -1, False))
            if at < 0 and end == start + 1:
                score = floor
            # An earlier start came first and wins ties.
            if (at >= 0 or end == start + 1) and base + score > best[end]:
                best[end], came[end], ids[end] = base + score, start, at
            if not more or end == stop:
                break
            end += 1
    out: list[int] = []
    at = n
    while at:
        if ids[at] < 0:
            out.extend(reversed(pieces.spell(word[at - 1 : at])))
        else:
            out.append(ids[at])
        at = came[at]
    out.reverse()
    return tuple(out)


def dictionary(df: DataFrame, pieces: Pieces, text: str = "text", size: int = DICTIONARY) -> dict[str, tuple[int, ...]]:
    """Ids of the most frequent words of all texts, ``size`` at most, by the relational lattice."""
    words = F.regexp_extract_all(marked(F.col(text)), F.lit(WORD), F.lit(0))
    # A floor follows from small histograms, so that no task sorts all words.
    counts = stage(df.select(F.explode(words).alias("word")).groupBy("word").agg(F.count("*").alias("n")), "piece-words")
    often = counts.where(F.col("n") >= least_often(counts, size))
    parts = 4 * df.sparkSession.sparkContext.defaultParallelism
    got = lattice(often.select("word").repartition(parts, "word"), pieces).toArrow()
    drop(counts)
    return {w: tuple(i) for w, i in zip(got.column("word").to_pylist(), got.column("ids").to_pylist(), strict=True)}


def least_often(counts: DataFrame, size: int) -> int:
    """The smallest ``n`` that no more than ``size`` words reach; counts by octave first, then inside the octave where it ends.

    Words of equal count stay together, so the dictionary may be smaller than ``size``.
    """
    octave = F.floor(F.log2("n")).cast("int")
    above = 0
    for at, words in sorted(counts.groupBy(octave.alias("at")).count().collect(), reverse=True):  # 63 rows at most
        if above + words > size:
            # The octave below 2 ** (at + 1), in 1024 steps at most.
            step = max(1, (1 << at) >> 10)
            inside = counts.where(octave == at).groupBy(F.floor(F.col("n") / step).alias("at")).count().collect()
            for low, more in sorted(inside, reverse=True):
                if above + more > size:
                    return (low + 1) * step
                above += more
            return 1 << at
        above += words
    return 1


class Words(dict):
    """Ids of words as bytes; words that the dictionary lacks are encoded when asked for, and kept up to a bound."""

    def __init__(self, pieces: Pieces, known: dict[str, bytes]):
        super().__init__(known)
        self.pieces, self.rare = pieces, []

    def __missing__(self, word: str) -> bytes:
        ids = np.array(word_ids(word, self.pieces), np.int32).tobytes()
        if len(self.rare) >= KEPT:
            for old in self.rare:
                self.pop(old, None)
            self.rare.clear()
        self.rare.append(word)
        self[word] = ids
        return ids


class Spelling:
    """The bytes of all pieces in one buffer, so that many ids decode in a few array operations."""

    def __init__(self, pieces: Pieces):
        parts = [pieces.raw.get(i, b"") for i in range(max(pieces.raw, default=0) + 1)]
        self.size = np.array([len(p) for p in parts], np.int64)
        self.start = np.concatenate(([0], np.cumsum(self.size)[:-1]))
        self.buffer = np.frombuffer(b"".join(parts), np.uint8)

    def text(self, ids: np.ndarray) -> bytes:
        """The bytes of ids, without the leading space."""
        if not len(ids):
            return b""
        sizes = self.size[ids]
        ends = np.cumsum(sizes)
        at = np.arange(ends[-1]) + np.repeat(self.start[ids] - (ends - sizes), sizes)
        return self.buffer[at].tobytes()[1:]


def encode(df: DataFrame, pieces: Pieces, id_col: str = "doc_id", text: str = "text", size: int = DICTIONARY) -> DataFrame:
    """``(id, ids, n_tokens, round_trip)``; ``round_trip`` says whether decoding gives the text back."""
    known = {w: np.array(i, np.int32).tobytes() for w, i in dictionary(df, pieces, text, size).items()}
    held = df.sparkSession.sparkContext.broadcast((vars(pieces), known))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, often = held.value
        own = Pieces.__new__(Pieces)
        own.__dict__ = state
        ids_of, split, spelling = Words(own, often).__getitem__, re.compile(WORD).findall, Spelling(own)
        for batch in batches:
            at = 0
            while at < batch.num_rows:  # slices of a batch, as ids outweigh their text
                ids: list[bytes | None] = []
                trips: list[bool | None] = []
                first, weight = at, 0
                while at < batch.num_rows and weight < SLICE:
                    t = batch.column("text")[at].as_py()
                    at += 1
                    if t is None:
                        ids.append(None)
                        trips.append(None)
                        continue
                    weight += len(t)
                    found = b"".join(map(ids_of, split(SPACE + t.replace(" ", SPACE)))) if t else b""
                    ids.append(found)
                    trips.append(spelling.text(np.frombuffer(found, np.int32)) == t.encode())
                sizes = np.array([0 if x is None else len(x) // 4 for x in ids], np.int64)
                ends = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
                null = pa.array([x is None for x in ids])
                values = pa.array(np.frombuffer(b"".join(x for x in ids if x), np.int32))
                lists = pa.ListArray.from_arrays(pa.array(ends), values, mask=null)
                lengths = pa.array(sizes, mask=null.to_numpy(zero_copy_only=False))
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(first, at - first), lists, lengths, pa.array(trips, pa.bool_())], names=["id", "ids", "n_tokens", "round_trip"])

    slim = df.select(F.col(id_col).alias("id"), F.col(text).alias("text"))
    kind = slim.schema["id"].dataType.simpleString()
    return slim.mapInArrow(run, f"id {kind}, ids array<int>, n_tokens long, round_trip boolean")


def decode(df: DataFrame, pieces: Pieces, ids: str = "ids", text: str = "text") -> DataFrame:
    """``df`` with ``text`` from ``ids``, in native expressions: the hexadecimal bytes of the pieces, joined and read back."""
    top = max(pieces.raw, default=0)
    table = F.from_json(F.lit(str([pieces.raw.get(i, b"").hex() for i in range(top + 1)]).replace("'", '"')), "array<string>")
    joined = F.array_join(F.transform(F.col(ids), lambda i: F.element_at(table, i + 1)), "")
    return df.withColumn(text, F.substring(F.decode(F.unhex(joined), "utf-8"), F.lit(2), F.length(joined)))
