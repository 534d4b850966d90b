"""Values that stand side by side are found each for itself."""

import hashlib
import re

import pytest
from pyspark.sql import functions as F

from shardweave.llm import pseudonyms


@pytest.mark.parametrize(
    "values",
    [
        ["+1 (826) 555-4081", "190.137.223.204"],
        ["+44 20 7946 0958", "170.106.47.218"],
        ["4929348385146306", "123"],
        ["12", "4929348385146306"],
        ["4929 3483 8514 6306"],
        ["+1 (826) 555-4081", "4929348385146306"],
    ],
)
def test_neighbours_stay_apart(spark, values):
    df = spark.createDataFrame([(" ".join(values),), *((v,) for v in values)], "text string")
    got = [r["text"] for r in pseudonyms.pseudonymise(df, "k").collect()]
    assert got[0] == " ".join(got[1:])
    assert all(new != old or len(old) < 4 for old, new in zip(values, got[1:], strict=True))


def swapped(text, tweak, key, hexes=False):
    """The network by loops over halves."""
    code = [int(c, 16) if hexes else ord(c) - (48 if c.isdigit() else 65 if c < "a" else 97) for c in text]
    radix = [16 if hexes else 10 if c.isdigit() else 26 for c in text]
    half = len(code) // 2
    for turn in range(8):
        low = turn % 2 == 0
        other = code[half:] if low else code[:half]
        digest = hashlib.sha512("|".join((key, tweak, str(turn), str(len(code)), ",".join(map(str, other)))).encode()).hexdigest()
        for j in range(half) if low else range(half, len(code)):
            at = (j % 16) * 8
            code[j] = (code[j] + int(digest[at : at + 8], 16)) % radix[j]
    if hexes:
        return "".join(f"{x:x}" for x in code)
    return "".join(chr(x + (48 if c.isdigit() else 65 if c < "a" else 97)) for c, x in zip(text, code, strict=True))


def test_the_network_equals_loops(spark):
    texts = ["7", "42", "0123456789", "aZ3", "DE370400440532013000XY", "9" * 40]
    got = spark.createDataFrame([(t,) for t in texts], "v string").select(pseudonyms.permute(F.col("v"), "t", "k").alias("w")).collect()
    assert [r["w"] for r in got] == [swapped(t, "t", "k") for t in texts]
    secret = "04dbebab91ab85687d33eeaaf9ac699e"
    row = spark.createDataFrame([(secret, secret.upper(), secret[:8].upper() + secret[8:])], "a string, b string, c string")
    a, b, c = row.select(*[pseudonyms.permute(F.col(n), "secret", "k", True) for n in "abc"]).first()
    assert a == swapped(secret, "secret", "k", True) and b == a.upper() and c.lower() == a and c != a


def told(spark, *values):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, text string")
    return [r["text"] for r in pseudonyms.pseudonymise(df, "k").orderBy("i").collect()]


def test_phones_link_however_they_are_written(spark):
    new = told(spark, "+1 (212) 555-7713", "+12125557713", "+1.212.555.7713", "(212) 555-7713", "212-555-7713")
    national = [re.sub(r"\D", "", v)[-10:] for v in new]
    assert len(set(national)) == 1 and national[0] != "2125557713" and new[0].startswith("+1 (") and new[1].startswith("+1")
    a, b = told(spark, "+44 20 7946 0958", "+442079460958")
    assert re.sub(r"\D", "", a) == re.sub(r"\D", "", b) and b.startswith("+44") and a != "+44 20 7946 0958"


def test_versions_are_no_addresses(spark):
    for text in ("version 1.2.3.4", "v1.2.3.4", "Release 10.0.1.2"):
        assert told(spark, text) == [text]
    assert told(spark, "host 10.0.1.2") != ["host 10.0.1.2"]


def test_keys(spark):
    df = spark.createDataFrame([("host 10.0.1.2", "a", "b")], "text string, _found string, _NEW string")
    got = pseudonyms.pseudonymise(df, "k").first()
    assert (got["_found"], got["_NEW"]) == ("a", "b") and got["text"] != pseudonyms.pseudonymise(df, "l").first()["text"]
    with pytest.raises(ValueError):
        pseudonyms.pseudonymise(df, "")
