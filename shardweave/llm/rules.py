"""Quality rules: a threshold table compiled into one projection of native expressions.

:func:`measures` gives each text its counts, :func:`verdict` compiles a rule table (numerator, denominator, bounds) into
one boolean column. No user function, no shuffle: every row is judged alone, so a run splits over any number of tasks.

Defined cases: a null or blank text has no words, fails the base rules and is rejected; a ratio over zero counts as zero;
repeated rows and repeated ids are judged row by row; an empty table gives an empty result; input columns whose names
clash with the measures or with ``base_failed``, ``kept`` and ``broken`` are replaced by them, all others are kept.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.llm.textcols import WORD, unused, words

#: Words in a window for the count of repeated words.
WINDOW = 5
#: Runs of anything but symbols.
NO_SYMBOLS = r"[^#*$%&|<>]+"

#: Frequent function words of English, French, Spanish and German.
STOP_WORDS = (
    "the and of to in is that for with as on at by an it was are be from or this which "
    "le la les de des du et un une que qui dans pour par sur au aux est avec elle "
    "el los las y en se con una para su al lo como por "
    "der die das und den von zu mit ein eine nicht ist auch als dem sich im auf"
).split()


@dataclass(frozen=True)
class Rule:
    """``low <= numerator / denominator <= high``; a bound of None is open. ``least``: it holds from so many words on."""

    name: str
    numerator: str
    denominator: str | None = None
    low: float | None = None
    high: float | None = None
    least: int = 0


#: The base rules hold always; the contract's ``base_failed`` is their negation.
BASE_RULES = (
    Rule("enough_words", "n_words", low=10),
    Rule("repeated_windows", "n_repeat_words", "n_words", high=0.20),
)

DEFAULT_RULES = (
    Rule("mean_word_length", "word_chars", "n_words", low=2.0, high=12.0),
    Rule("symbols_per_word", "n_symbols", "n_words", high=0.10),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", high=0.40),
    Rule("stop_words", "n_stop_words", "n_words", low=0.02, least=50),
    Rule("shouted_words", "n_shouted", "n_words", high=0.30),
)


def _window_hashes(w: Column) -> Column:
    """A 64-bit hash of each window of :data:`WINDOW` words; none for shorter texts."""
    starts = F.size(w) - (WINDOW - 1)
    hashes = F.transform(F.sequence(F.lit(1), starts), lambda i: F.xxhash64(F.slice(w, i, WINDOW)))
    return F.when(starts < 2, F.array().cast("array<bigint>")).otherwise(hashes)


def _tagged(h: Column) -> Column:
    """Hashes with their positions, equal ones side by side; null where none repeats, which spares most rows the sort."""
    pairs = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(h)) < F.size(h), pairs)


def _positions(tagged: Column) -> Column:
    """Ascending start positions of windows that occur twice or more."""

    def of(t: Column) -> Column:
        def repeated(x: Column, j: Column) -> Column:
            before, after = F.get(t, j - 1).h, F.get(t, j + 1).h
            return F.coalesce(x.h == before, F.lit(False)) | F.coalesce(x.h == after, F.lit(False))

        return F.array_sort(F.transform(F.filter(t, repeated), lambda x: x.i))

    # A lambda's variable is worked out once, even where the optimiser inlines the column.
    return F.get(F.transform(F.array(tagged), of), F.lit(0))


def _covered(at: Column) -> Column:
    """How many positions the windows that start at ``at`` cover."""
    gaps = F.transform(at, lambda i, j: F.least(F.lit(WINDOW), F.coalesce(F.get(at, j + 1) - i, F.lit(WINDOW))))
    return F.coalesce(F.aggregate(gaps, F.lit(0), lambda s, x: s + x), F.lit(0))


def measures(df: DataFrame, text: str = "text") -> DataFrame:
    """``df`` with the counts that rules refer to, all long."""
    t = F.coalesce(F.col(text), F.lit(""))
    bare = df.drop(*MEASURES)
    found, lines, hashes, tagged, at = unused(bare, "_w", "_lines", "_h", "_tagged", "_at")
    out = bare.withColumns({found: words(t), lines: F.filter(F.split(t, "\n", -1), lambda x: x.rlike(WORD))})
    out = out.withColumn(hashes, _window_hashes(F.col(found)))
    out = out.withColumn(tagged, _tagged(F.col(hashes)))
    out = out.withColumn(at, _positions(F.col(tagged)))
    w = F.col(found)
    counts = {
        # Always true, but not deterministic: filters on the verdict stay above this projection and don't repeat it.
        "n_words": F.when(F.spark_partition_id() >= 0, F.size(w)),
        "word_chars": F.length(F.array_join(w, "")),
        "n_symbols": F.length(F.regexp_replace(t, NO_SYMBOLS, "")),
        "n_lines": F.size(lines),
        "n_dup_lines": F.size(lines) - F.size(F.array_distinct(lines)),
        "n_stop_words": F.size(F.filter(w, lambda x: F.lower(x).isin(STOP_WORDS))),
        "n_shouted": F.size(F.filter(w, lambda x: x.endswith("!!"))),
        "n_repeat_words": _covered(F.col(at)),
    }
    return out.withColumns({k: v.cast("long") for k, v in counts.items()}).drop(found, lines, hashes, tagged, at)

MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_stop_words", "n_shouted", "n_repeat_words")


def passes(rule: Rule) -> Column:
    """One rule as a boolean column; the comparison is by products, so integer counts compare exactly at round bounds."""
    top = F.col(rule.numerator)
    below = F.col(rule.denominator) if rule.denominator else F.lit(1)
    ok = F.lit(True)
    if rule.low is not None:
        ok = ok & (top >= F.lit(rule.low) * below)
    if rule.high is not None:
        ok = ok & (top * 100 <= F.lit(round(rule.high * 100, 6)) * below)
    return ok | (F.col("n_words") < rule.least) if rule.least else ok


def verdict(rules: tuple[Rule, ...]) -> Column:
    out = F.lit(True)
    for rule in rules:
        out = out & passes(rule)
    return out


def judge(df: DataFrame, text: str = "text", rules: tuple[Rule, ...] = DEFAULT_RULES, base: tuple[Rule, ...] = BASE_RULES) -> DataFrame:
    """``df`` with the measures, ``base_failed``, ``kept`` and ``broken``, the names of the rules that a row breaks."""
    out = measures(df, text)
    broken = F.filter(F.array(*[F.when(~passes(r), F.lit(r.name)) for r in (*base, *rules)]), lambda x: x.isNotNull())
    failed = ~verdict(base)
    return out.withColumns({"base_failed": failed, "kept": ~failed & verdict(rules), "broken": broken})
