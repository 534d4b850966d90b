"""Column expressions over text that several operators share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space that ends a word, and a word's pattern in Java, RE2 and Python.
SPACE = " \t\n\x0b\f\r"
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def words(text: Column) -> Column:
    """The words of a text in order; an empty array for null, empty and blank texts."""
    bare = F.trim(text, F.lit(SPACE))
    empty = F.array().cast("array<string>")
    return F.when(F.coalesce(bare, F.lit("")) == "", empty).otherwise(F.split(bare, GAP, -1))


def word_count(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(df: DataFrame, *names: str) -> list[str]:
    """Names for working columns: those given, with underscores behind as long as an input column has the name."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def boxed(df: DataFrame) -> Column:
    """All columns of a frame as one, so that working columns beside it never clash."""
    return F.struct(*[F.col(f"`{c}`") for c in df.columns])
