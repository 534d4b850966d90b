"""PII: format-preserving Feistel pseudonyms, in native expressions only.

Numbers and dates are found by pattern, validated (Luhn, mod 97, octets, calendar, number ranges) and permuted under a key
within their own format: a card stays a card with a right check digit, a date stays a date. The permutation is a Feistel
network over symbols with a radix each, so it is a bijection of the format, and equal values get equal pseudonyms in every
document, however they are spaced: of a phone number only the digits count, less the country code, which stays (so a number
of the code 1 links with and without it). Local parts of mail addresses and hexadecimal secrets are permuted the same way.
The caller gives the key.

No shuffle and no Python: a text is split at its matches, each match is replaced, and the pieces are joined again. Texts
without a digit or an at sign skip all that.

Defined cases: null texts stay null and have no findings, empty texts stay empty; values that fail validation stay as they
are; dates are permuted from 1900-01-01 to 2099-12-30 and stay outside of it; repeated rows get equal results; an empty
table gives an empty result; the count column replaces an input column of that name, all others are kept; four numbers behind
a word for a version are no address.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.llm.textcols import unused

ROUNDS = 8
#: Of the international country codes those of one and of two digits; all others have three.
CODES_1 = "17"
CODES_2 = "20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()
#: Dates in the permuted range as two symbols: 8 * 9131 days from 1900-01-01.
DAY_ZERO, DAY_RADIX = "1900-01-01", (8, 9131)

EMAIL = r"[\p{L}\p{N}._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
SECRET = r"\b(?=[A-Fa-f]*[0-9])[0-9A-Fa-f]{32,64}\b"
IBAN = r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b"
IP = r"(?<![0-9.])(?<!\b[Vv])(?<!\b(?i:v|ver|version|release|build)[.:]? )(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?!\.?[0-9])"
ISO = r"\b[0-9]{4}-[0-9]{2}-[0-9]{2}\b"
SLASHED = r"(?<![0-9/])[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}(?![0-9/])"
DOTTED = r"(?<![0-9.])[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4}(?!\.?[0-9])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
#: Ten digits behind +1; other countries have no fixed lengths, but an address behind the number is not a part of it.
PHONE = (
    r"\+1[ .-]?\(?[0-9]{3}\)?[ .-]?[0-9]{3}[ .-]?[0-9]{4}(?![0-9])"
    r"|\+[0-9]{1,3}[ .-]?\(?[0-9]{2,4}\)?(?:[ .-]?(?!(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?!\.?[0-9]))[0-9]{2,4}){2,4}(?![0-9])"
    r"|\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}(?![0-9])|(?<![0-9-])[0-9]{3}-[0-9]{3}-[0-9]{4}(?![0-9-])"
)
#: A run of 13 to 19 digits before digits joined over marks, which don't reach into such a run behind them.
CARD = r"(?<![0-9])[0-9]{13,19}(?![0-9])|(?<![0-9])(?!(?:[0-9]{1,12}[ -]){1,3}[0-9]{13,19}(?![0-9]))[0-9](?:[ -]?[0-9]){12,18}(?![0-9])"

#: In order of precedence; the first that matches at a place wins it.
PATTERNS = {"email": EMAIL, "secret": SECRET, "iban": IBAN, "ip": IP, "iso": ISO, "slashed": SLASHED, "dotted": DOTTED, "ssn": SSN, "phone": PHONE, "card": CARD}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())

DIGIT, ALNUM, HEX = "[0-9]", "[0-9A-Za-z]", "[0-9A-Fa-f]"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is worked out once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def chars(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit("(?s)."), F.lit(0))


def feistel(symbols: Column, radix: Column, tweak: str, key: str) -> Column:
    """Permute an array of longs, each within its radix: halves add keyed digests of each other in turn."""

    def step(state: Column, turn: Column) -> Column:
        half = F.floor(F.size(state) / 2).cast("int")
        low = (turn % 2) == 0
        other = F.when(low, F.slice(state, half + 1, F.size(state) - half)).otherwise(F.slice(state, F.lit(1), half))
        said = F.concat_ws("|", F.lit(key), F.lit(tweak), turn.cast("string"), F.size(state).cast("string"), F.array_join(F.transform(other, lambda x: x.cast("string")), ","))

        def shifted(digest: Column) -> Column:
            def move(x: Column, j: Column) -> Column:
                by = F.conv(F.substring(digest, (j % 16) * 8 + 1, F.lit(8)), 16, 10).cast("long")
                return F.when((j < half) == low, (x + by) % F.get(radix, j)).otherwise(x)

            return F.transform(state, move)

        return let(F.sha2(said, 512), shifted)

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), symbols, step)


def _place(c: Column, hexes: bool) -> Column:
    """A character's number inside its class."""
    if hexes:
        return F.conv(c, 16, 10).cast("long")
    code = F.ascii(c)
    return F.when(code < 65, code - 48).when(code < 97, code - 65).otherwise(code - 97).cast("long")


def _glyph(c: Column, x: Column, hexes: bool) -> Column:
    """The character number ``x`` of the class of ``c``."""
    if hexes:
        return F.lower(F.conv(x.cast("string"), 10, 16))
    code = F.ascii(c)
    base = F.when(code < 65, 48).when(code < 97, 65).otherwise(97)
    return F.chr(base + x)


def permute(text: Column, tweak: str, key: str, hexes: bool = False) -> Column:
    """A string of letters and digits permuted, each character within its class."""
    radix = (lambda c: F.lit(16).cast("long")) if hexes else (lambda c: F.when(F.ascii(c) < 65, 10).otherwise(26).cast("long"))

    def of(cs: Column) -> Column:
        moved = feistel(F.transform(cs, lambda c: _place(c, hexes)), F.transform(cs, radix), tweak, key)
        return F.array_join(F.zip_with(cs, moved, lambda c, x: _glyph(c, x, hexes)), "")

    out = let(chars(text), of)
    if not hexes:
        return out
    # Letters keep the case of their place; where a digit was, that of the whole, small in mixed ones.
    cased = F.zip_with(chars(text), chars(out), lambda c, x: F.when(c.rlike("[A-F]"), F.upper(x)).otherwise(x))
    return F.when(text == F.upper(text), F.upper(out)).when(text == F.lower(text), out).otherwise(F.array_join(cased, ""))


def only(text: Column, kind: str) -> Column:
    return F.array_join(F.regexp_extract_all(text, F.lit(kind), F.lit(0)), "")


def inject(text: Column, kind: str, new: Column) -> Column:
    """``text`` with its characters of a class replaced, in order, by those of ``new``."""

    def put(cs: Column) -> Column:
        def one(c: Column, i: Column) -> Column:
            at = F.size(F.filter(F.slice(cs, F.lit(1), i + 1), lambda x: x.rlike(kind)))
            return F.when(c.rlike(kind), F.substring(new, at, F.lit(1))).otherwise(c)

        return F.array_join(F.transform(cs, one), "")

    return let(chars(text), put)


def luhn(digits: Column) -> Column:
    """The Luhn sum of a string of digits."""
    doubled = F.transform(
        F.reverse(chars(digits)), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0))
    )
    return F.aggregate(doubled, F.lit(0), lambda s, x: s + x)


def mod97(text: Column) -> Column:
    def add(s: Column, c: Column) -> Column:
        return F.when(c.rlike(DIGIT), (s * 10 + c.try_cast("int")) % 97).otherwise((s * 100 + F.ascii(c) - 55) % 97)

    return F.aggregate(chars(text), F.lit(0), add)


def _email(v: Column, key: str) -> Column:
    local, domain = F.substring_index(v, "@", 1), F.substring_index(v, "@", -1)
    return F.concat(let(local, lambda x: inject(x, ALNUM, permute(only(x, ALNUM), "email", key))), F.lit("@"), domain)


def _secret(v: Column, key: str) -> Column:
    return permute(v, "secret", key, hexes=True)


def _card(v: Column, key: str) -> Column:
    def of(d: Column) -> Column:
        body = permute(F.substring(d, F.lit(1), F.length(d) - 1), "card", key)
        whole = let(body, lambda b: F.concat(b, ((10 - luhn(F.concat(b, F.lit("0"))) % 10) % 10).cast("string")))
        return F.when(luhn(d) % 10 == 0, let(whole, lambda w: inject(v, DIGIT, w))).otherwise(v)

    return let(only(v, DIGIT), of)


def _iban(v: Column, key: str) -> Column:
    def of(d: Column) -> Column:
        land, rest = F.substring(d, 1, 2), F.substring(d, F.lit(5), F.length(d))

        def whole(b: Column) -> Column:
            check = F.lpad((98 - mod97(F.concat(b, land, F.lit("00")))).cast("string"), 2, "0")
            return F.concat(land, check, b)

        good = mod97(F.concat(rest, F.substring(d, 1, 4))) == 1
        new = let(let(permute(rest, "iban", key), whole), lambda w: inject(v, ALNUM, w))
        return F.when(good, new).otherwise(v)

    return let(only(v, ALNUM), of)


def _ip(v: Column, key: str) -> Column:
    def of(parts: Column) -> Column:
        new = feistel(parts, F.transform(parts, lambda x: F.lit(256).cast("long")), "ip", key)
        return F.when(F.forall(parts, lambda x: x < 256), F.array_join(F.transform(new, lambda x: x.cast("string")), ".")).otherwise(v)

    return let(F.transform(F.split(v, r"\."), lambda x: x.cast("long")), of)


def _phone(v: Column, key: str) -> Column:
    """The digits behind the country code, which only numbers with a plus have."""

    def of(d: Column) -> Column:
        code = F.when(~v.startswith("+"), 0).when(F.substring(d, 1, 1).isin(*CODES_1), 1).when(F.substring(d, 1, 2).isin(CODES_2), 2).otherwise(3)
        new = let(code, lambda n: F.concat(F.substring(d, F.lit(1), n), permute(F.substring(d, n + 1, F.length(d)), "phone", key)))
        return let(new, lambda w: inject(v, DIGIT, w))

    return let(only(v, DIGIT), of)


def _ssn(v: Column, key: str) -> Column:
    def of(p: Column) -> Column:
        area, group, serial = (F.get(p, F.lit(i)) for i in range(3))
        good = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
        own = F.array(area - F.when(area > 666, 2).otherwise(1), group - 1, serial - 1)
        radix = F.array(*[F.lit(n).cast("long") for n in (898, 99, 9999)])

        def shown(n: Column) -> Column:
            a = F.get(n, F.lit(0)) + 1
            pad = lambda x, w: F.lpad(x.cast("string"), w, "0")
            return F.concat_ws("-", pad(a + F.when(a >= 666, 1).otherwise(0), 3), pad(F.get(n, F.lit(1)) + 1, 2), pad(F.get(n, F.lit(2)) + 1, 4))

        return F.when(good, let(feistel(own, radix, "ssn", key), shown)).otherwise(v)

    return let(F.transform(F.split(v, "-"), lambda x: x.cast("long")), of)


def _date(v: Column, mark: str, key: str) -> Column:
    """A date with ``mark`` between its parts: year first with a hyphen, else month first where that is a date with a slash."""

    def of(p: Column) -> Column:
        a, b, c = (F.get(p, F.lit(i)) for i in range(3))
        make = lambda y, m, d: F.try_to_date(F.concat_ws("-", F.lpad(y, 4, "0"), F.lpad(m, 2, "0"), F.lpad(d, 2, "0")), "yyyy-MM-dd")
        month_first = make(c, a, b).isNotNull() if mark == "/" else F.lit(False)
        day = make(a, b, c) if mark == "-" else F.when(month_first, make(c, a, b)).otherwise(make(c, b, a))

        def moved(n: Column) -> Column:
            wide = F.lit(DAY_RADIX[1]).cast("long")
            own = F.array(F.floor(n / wide), n % wide)
            radix = F.array(*[F.lit(x).cast("long") for x in DAY_RADIX])

            def shown(m: Column) -> Column:
                new = F.date_add(F.lit(DAY_ZERO).cast("date"), (F.get(m, F.lit(0)) * wide + F.get(m, F.lit(1))).cast("int"))
                y, mm, dd = F.date_format(new, "yyyy"), F.date_format(new, "MM"), F.date_format(new, "dd")
                return F.concat_ws(mark, y, mm, dd) if mark == "-" else F.when(month_first, F.concat_ws(mark, mm, dd, y)).otherwise(F.concat_ws(mark, dd, mm, y))

            return let(feistel(own, radix, "date", key), shown)

        since = F.date_diff(day, F.lit(DAY_ZERO).cast("date")).cast("long")
        return let(since, lambda n: F.when(n.between(0, DAY_RADIX[0] * DAY_RADIX[1] - 1), moved(n)).otherwise(v))

    return let(F.split(v, r"\." if mark == "." else mark), of)


MAKERS: dict[str, Callable[[Column, str], Column]] = {
    "email": _email, "secret": _secret, "iban": _iban, "ip": _ip, "iso": lambda v, k: _date(v, "-", k), "slashed": lambda v, k: _date(v, "/", k),
    "dotted": lambda v, k: _date(v, ".", k), "ssn": _ssn, "phone": _phone, "card": _card,
}


def pseudonym(value: Column, key: str) -> Column:
    """The pseudonym of one found value, or the value where it isn't valid."""
    out = value
    for kind, pattern in reversed(PATTERNS.items()):
        out = F.when(value.rlike(rf"^(?:{pattern})$"), MAKERS[kind](value, key)).otherwise(out)
    return out


def pseudonymise(df: DataFrame, key: str, text: str = "text", count: str = "n_private") -> DataFrame:
    """``df`` with private values in ``text`` replaced under ``key``, and how many were."""
    if not key:
        raise ValueError("pseudonyms need a key")
    t = F.col(text)
    bare = df.drop(count)
    found, new = unused(bare, "_found", "_new")
    out = bare.withColumn(found, F.when(t.rlike("[0-9@]"), F.regexp_extract_all(t, F.lit(ANY), F.lit(0))))
    out = out.withColumn(new, F.transform(found, lambda v: pseudonym(v, key)))
    parts = F.zip_with(F.split(t, ANY, -1), F.col(new), lambda gap, value: F.concat(gap, F.coalesce(value, F.lit(""))))
    n = F.size(F.filter(F.zip_with(found, new, lambda a, b: a != b), lambda x: x))
    changed = F.coalesce(n, F.lit(0)) > 0
    return out.withColumns({text: F.when(changed, F.array_join(parts, "")).otherwise(t), count: F.when(changed, n).otherwise(0).cast("long")}).drop(found, new)
