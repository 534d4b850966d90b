"""Mixing sources to target weights by weighted sampling without replacement.

Sources get token budgets in proportion to their weights; a budget stops at a multiple of its source's size and the excess
goes to the others by weight. A budget is filled by whole epochs first. The rest is a fractional epoch: each document
draws an exponential key divided by its quality weight, keys are ordered within the source, sizes prefix-summed, and
documents are taken while the middle of their span lies inside the rest. So a source misses its budget by at most half a
document, and a document is taken at most one time more than the full epochs.

The order inside a source is never held by one task. Keys map to whole numbers in the same order; their leading bits are
bins, whose sums are prefix-summed; the bin where a budget ends is split by its next bits, and again, until few rows are
left in it (or equal keys alone, which are summed up before they are ranked). So it doesn't matter how keys lie, and a source
that holds most rows costs no more than the others. Draws follow from a seed, the id and a digest of the text: reruns agree.

Defined cases: null sources form one source, the last in order; null and blank texts have size 0 and are never taken in
part; equal rows draw equal keys and are taken alike; an empty table gives an empty result; input columns named like the
added ones are replaced, all others are kept whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shardweave.llm import rules
from shardweave.llm.textcols import WORD, boxed, words
from shardweave.staging import drop, stage

CYCLE = (5.0, 2.0, 1.0)
MAX_EPOCHS = 3.0
#: Bits of a key's number, bits that a level of bins takes, and rows of a bin that may be ranked at once.
KEY_BITS, LEVEL_BITS, EDGE_ROWS = 48, 12, 50_000
SALTS = 32
#: Rows (one a source) that a broadcast may have: under 1 MB.
BROADCAST_ROWS = 10_000
ADDED = ("size", "source_size", "target", "taken")


def uniform(*parts: Column, seed: int = 42) -> Column:
    """A number inside (0, 1) with 52 bits from the digest of seed and parts."""
    text = F.concat_ws("|", F.lit(str(seed)), *[F.coalesce(p.cast("string"), F.lit("null")) for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def quality_weight(text: Column, found: Column) -> Column:
    """What the rules measure as one weight, 0.05 to 1: the share of letters, less the shares of repeated lines and of symbols."""
    letters = F.length(F.regexp_replace(text, r"[^\p{L}]+", "")).cast("double")
    symbols = F.length(F.regexp_replace(text, rules.NO_SYMBOLS, "")).cast("double")
    lines = F.filter(F.split(text, "\n", -1), lambda x: x.rlike(WORD))
    whole = lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0))
    again = F.get(F.transform(F.array(lines), lambda x: whole((F.size(x) - F.size(F.array_distinct(x))).cast("double"), F.size(x))), F.lit(0))
    clean = 1 - F.least(F.lit(1.0), whole(symbols, F.size(found)))
    return F.greatest(F.lit(0.05), whole(letters, F.length(text)) * (1 - again) * clean)


def budgets(sizes: DataFrame, source: str, weights: tuple[float, ...] = CYCLE, share: float = 1.0, most: float = MAX_EPOCHS) -> DataFrame:
    """``sizes`` (one row a source: source, source_size) with ``target``.

    Sources in order of name, null last, weigh ``weights``, repeating. The final targets are min(cap, level * weight) with
    one level for all; sorted by cap / weight, the capped sources come first, so running sums find the level.
    One row a source goes through one task here.
    """
    if not weights or min(weights) <= 0:
        raise ValueError("weights must be positive")
    by_name = Window.orderBy(F.col(source).asc_nulls_last())
    turn = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights)))
    weighed = sizes.withColumn("_weight", F.element_at(F.array(*map(F.lit, weights)), turn + 1))
    weighed = weighed.withColumn("_cap", F.col("source_size") * F.lit(most))
    every = Window.partitionBy()
    up = Window.orderBy(F.col("_cap") / F.col("_weight"), F.col(source).asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    stepped = weighed.withColumns(
        {
            "_goal": F.sum("source_size").over(every) * F.lit(share),
            "_capped": F.coalesce(F.sum("_cap").over(up), F.lit(0.0)),
            "_left": F.sum("_weight").over(every) - F.coalesce(F.sum("_weight").over(up), F.lit(0.0)),
        }
    )
    reached = stepped.withColumn("_level", (F.col("_goal") - F.col("_capped")) / F.col("_left"))
    # The first source that its own level doesn't cap sets the level of all that follow.
    level = F.min(F.when(F.col("_cap") > F.col("_level") * F.col("_weight"), F.struct((F.col("_cap") / F.col("_weight")).alias("r"), "_level"))).over(every)
    target = F.least(F.col("_cap"), F.coalesce(level["_level"], F.lit(float("inf"))) * F.col("_weight"))
    return reached.withColumn("target", target).select(source, "source_size", "target")


def draw(df: DataFrame, id_col: str, text: str, source: str, quality: Column | None, seed: int) -> DataFrame:
    """``(row, id, source, size, key)``: the row as it came, its size, and its exponential key over the quality weight."""
    plain = F.coalesce(F.col(text), F.lit(""))
    given = (quality,) if quality is not None else ()
    asked = df.select(boxed(df.drop(*ADDED)).alias("row"), F.col(id_col).cast("string").alias("id"), F.col(source).alias("source"), plain.alias("text"), *[q.cast("double").alias("quality") for q in given])
    asked = asked.withColumn("words", words(F.col("text")))
    weight = F.col("quality") if given else quality_weight(F.col("text"), F.col("words"))
    key = -F.log(uniform(F.col("id"), F.md5("text"), seed=seed)) / weight
    return asked.select("row", "id", "source", F.size("words").cast("long").alias("size"), key.alias("key"))


def place(key: Column) -> Column:
    """A key as a whole number of ``KEY_BITS`` bits that never falls as the key rises."""
    return F.floor(key / (key + 1) * float((1 << KEY_BITS) - 1)).cast("long")


def entry() -> Column:
    """The order inside a source; the id as text, null as the empty one."""
    return F.struct(F.col("key"), F.coalesce(F.col("id"), F.lit("")).alias("id"), F.col("size"))


def plan(slim: DataFrame, weights: tuple[float, ...], share: float, most: float, edge_rows: int = EDGE_ROWS) -> DataFrame:
    """One row a source, ``(goal, source_size, target, epochs, cut)``: the last entry that the fractional epoch takes.

    ``slim`` is a written table ``(id, source, size, key)``.
    """
    goals = budgets(slim.groupBy("source").agg(F.sum("size").alias("source_size")), "source", weights, share, most)
    goals = goals.withColumn("epochs", F.floor(F.coalesce(F.try_divide(F.col("target"), F.col("source_size")), F.lit(0.0))))
    goals = stage(goals.select(F.col("source").alias("goal"), "source_size", "target", "epochs", (F.col("target") - F.col("epochs") * F.col("source_size")).alias("rest")), "mix-goals")
    rows = slim.select("id", "source", "size", "key", place(F.col("key")).alias("place"))
    # Per source the bin in which its budget ends, by its leading bits, and what lies before it.
    ends = stage(goals.where("rest > 0").select("goal", "rest", F.lit(0).cast("long").alias("bin"), F.lit(0).cast("long").alias("start")), "mix-ends")
    shift, edge = KEY_BITS, None
    while shift > 0:
        inside = met(rows, ends, "source", "goal").where(F.shiftright("place", shift) == F.col("bin")) if shift < KEY_BITS else met(rows, ends, "source", "goal")
        shift -= LEVEL_BITS
        binned = inside.groupBy("goal", "rest", "start", F.shiftright("place", shift).alias("own")).agg(F.sum("size").alias("sum"), F.count("*").alias("n"))
        up = Window.partitionBy("goal").orderBy("own").rowsBetween(Window.unboundedPreceding, -1)
        before = binned.withColumn("before", F.col("start") + F.coalesce(F.sum("sum").over(up), F.lit(0)))
        reached = before.where("before <= rest and sum > 0").groupBy("goal", "rest").agg(F.max(F.struct("own", "before", "n")).alias("end"))
        found = stage(reached.select("goal", "rest", F.col("end.own").alias("bin"), F.col("end.before").alias("start"), F.col("end.n").alias("n")), "mix-ends")
        drop(ends)
        ends = found
        if (ends.agg(F.max("n")).first()[0] or 0) <= edge_rows:
            break
    edge = met(rows, ends.drop("n"), "source", "goal").where(F.shiftright("place", shift) == F.col("bin"))
    # Equal entries count as one, so that a group of copies is no window of its own.
    once = edge.groupBy("goal", "rest", "start", entry().alias("entry")).agg(F.sum("size").alias("sum"))
    run = Window.partitionBy("goal").orderBy("entry").rowsBetween(Window.unboundedPreceding, -1)
    middle = F.col("start") + F.coalesce(F.sum("sum").over(run), F.lit(0)) + F.col("entry.size") / 2.0
    cuts = once.withColumn("middle", middle).where("middle <= rest").groupBy(F.col("goal").alias("of")).agg(F.max("entry").alias("cut"))
    # Where the first entry of the last bin is already too much, all of the bins before it are taken.
    ends = ends.select(F.col("goal").alias("of"), F.col("bin").alias("last"), F.lit(shift).alias("shift"))
    out = goals.drop("rest").join(ends, goals["goal"].eqNullSafe(ends["of"]), "left").drop("of")
    return out.join(cuts, out["goal"].eqNullSafe(cuts["of"]), "left").drop("of")


def met(rows: DataFrame, per_source: DataFrame, source: str, other: str) -> DataFrame:
    """``rows`` joined to a table of one row a source: broadcast after its rows are counted, salted beyond that."""
    if per_source.count() <= BROADCAST_ROWS:
        return rows.join(F.broadcast(per_source), rows[source].eqNullSafe(per_source[other]))
    salted = per_source.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    left = rows.withColumn("grain", F.pmod(F.xxhash64("key"), F.lit(SALTS)).cast("int"))
    return left.join(salted, left[source].eqNullSafe(salted[other]) & (left["grain"] == salted["salt"])).drop("salt", "grain")


def _taken(drawn: DataFrame, slim: DataFrame, weights: tuple[float, ...], share: float, most: float, edge_rows: int) -> DataFrame:
    """``drawn`` with source_size, target and taken."""
    goals = stage(plan(slim, weights, share, most, edge_rows), "mix-plan")
    out = met(drawn, goals, "source", "goal")
    own = F.expr("shiftright(place, shift)")
    chosen = (own < F.col("last")) | ((own == F.col("last")) & F.coalesce(entry() <= F.col("cut"), F.lit(False)))
    times = F.col("epochs") + F.coalesce(chosen, F.lit(False)).cast("long")
    return out.withColumn("place", place(F.col("key"))).withColumn("taken", (F.col("size") * times).cast("long"))


def mix(
    df: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[float, ...] = CYCLE, share: float = 1.0, most: float = MAX_EPOCHS,
    quality: Column | None = None, seed: int = 42, edge_rows: int = EDGE_ROWS,
) -> DataFrame:
    """``df`` with size, source_size, target, and taken: the words that the mix takes of each document.

    ``quality`` is the weight of a row, above zero; without it, :func:`quality_weight` of its text. Texts are read twice: for
    the draws, which are written without them, and for the result.
    """
    drawn = draw(df, id_col, text, source, quality, seed)
    slim = stage(drawn.select("id", "source", "size", "key"), "mix")
    return _taken(drawn, slim, weights, share, most, edge_rows).select("row.*", *ADDED)


def shares(
    df: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[float, ...] = CYCLE, share: float = 1.0, most: float = MAX_EPOCHS,
    quality: Column | None = None, seed: int = 42, edge_rows: int = EDGE_ROWS,
) -> DataFrame:
    """:func:`mix` without the texts, ``(id, source, size, source_size, target, taken)`` by the names of ``df``: texts are read once."""
    drawn = draw(df.select(id_col, source, text), id_col, text, source, quality, seed)
    slim = stage(drawn.select(F.col(f"row.{id_col}").alias("named"), "id", "source", "size", "key"), "mix")
    return _taken(slim, slim, weights, share, most, edge_rows).select(F.col("named").alias(id_col), F.col("source").alias(source), *ADDED)


def rows_of(mixed: DataFrame) -> DataFrame:
    """A mix as rows: each document as often as the mix takes it."""
    times = F.when(F.col("size") > 0, (F.col("taken") / F.col("size")).cast("int")).otherwise(0)
    copies = mixed.select(boxed(mixed.drop(*ADDED)).alias("row"), times.alias("times")).where("times > 0")
    return copies.select("row", F.explode(F.sequence(F.lit(1), F.col("times")))).select("row.*")
