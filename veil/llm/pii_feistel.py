"""Format-preserving pseudonyms by keyed Feistel networks (native).

Card numbers, telephone numbers, social security numbers, addresses of the
fourth internet protocol and calendar dates are recognised, validated, mapped
to an index of their format's domain, permuted there by a keyed network over
two uneven halves, and written back in the same layout, check digit included.
A permutation keeps different values different and equal values equal in every
document; with the key it can be undone (``reveal``).

Mail addresses and secrets (access keys, passwords, tokens) have no numeric
domain: they become keyed digests in the same layout, so they stay linked too,
but cannot be undone.

One alternation finds all kinds in one scan. Matches start at token starts
only, and runs of any length are taken whole, so no part of a long secret stays
and a scan stays linear on very long texts. Texts without a find are returned as they are. No shuffle, no Python.

Defined results: null texts stay null, empty texts empty; finds that fail
validation are left alone; repeated rows are rewritten alike; extra columns
pass through; an empty table gives an empty table. Not covered: IBANs, addresses
of the sixth internet protocol, dates in other layouts than year-month-day,
numbers of other countries and ten bare digits.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 10
DEFAULT_KEY = "example key: give your own"

#: Fixed patterns, one per kind, in order of precedence.
PATTERNS = {
    "mail": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "access_key": r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])",
    "password": r"(?<![A-Za-z0-9_])(?i:password|passwd|pwd|secret)[=:][^\x20\x09-\x0D]{3,}[^\x20\x09-\x0D.,;:!?)\]\"']",
    "token": r"(?<![A-Za-z0-9_])(?i:token|api[_-]?key|secret)\x20{0,2}[=:]\x20{0,2}[\"'][A-Za-z0-9._/+=-]{8,}+[\"']",
    "ip": r"(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9])(?!\.[0-9])",
    "phone": r"(?<![0-9A-Za-z])\+1\x20\([2-9][0-9]{2}\)\x20[2-9][0-9]{2}-[0-9]{4}(?![0-9])|(?<![0-9A-Za-z+])\([2-9][0-9]{2}\)\x20[2-9][0-9]{2}-[0-9]{4}(?![0-9])|(?<![0-9A-Za-z.-])(?:\+1[-.\x20]|1[-.])?[2-9][0-9]{2}(?<ps>[-.])[2-9][0-9]{2}\k<ps>[0-9]{4}(?![0-9])(?![-.][0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9])(?!-[0-9])",
    "date": r"(?<![0-9-])(?:19|20)[0-9]{2}-[0-9]{2}-[0-9]{2}(?![0-9])(?!-[0-9])",
    "card": r"(?<![0-9A-Za-z])[0-9]{4}(?<cs>[\x20-])[0-9]{4}\k<cs>[0-9]{4}\k<cs>[0-9]{4}(?![0-9])|(?<![0-9A-Za-z.])[0-9]{13,19}(?![0-9A-Za-z])",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Cheap test that a text can hold a find at all.
HINT = r"[0-9@]|(?i:password|passwd|pwd|secret|token|api[_-]?key)"
HEX, LETTERS = "0123456789abcdef", "ABCDEFGHIJKLMNOP"


@dataclass(frozen=True)
class Domain:
    """Indexes 0 .. left*right-1, split as index = l * right + r."""

    kind: str
    left: int
    right: int


IP = Domain("ip", 1 << 16, 1 << 16)
PHONE = Domain("phone", 80_000, 80_000)
SSN = Domain("ssn", 898 * 99, 9_999)
DATE = Domain("date", 17, 4_297)
FIRST_DAY = "1900-01-01"


def permute(index: Column, left: Column, right: Column, kind: str, key: str, undo: bool = False) -> Column:
    """Keyed permutation of 0 .. left*right-1.

    Even rounds add a keyed digest of the right half to the left one, odd
    rounds the other way; undoing subtracts in reverse order.
    """

    def digest(i: Column, half: Column) -> Column:
        h = F.sha2(F.concat_ws("|", F.lit(key), F.lit(kind), i.cast("string"), half.cast("string")), 256)
        return F.conv(F.substr(h, F.lit(1), F.lit(12)), 16, 10).cast("long")

    def turn(half: Column, other: Column, size: Column, i: Column) -> Column:
        d = digest(i, other)
        return F.pmod(half - d if undo else half + d, size)

    def step(acc: Column, i: Column) -> Column:
        left_turn = F.struct(turn(acc["l"], acc["r"], left, i).alias("l"), acc["r"].alias("r"))
        right_turn = F.struct(acc["l"].alias("l"), turn(acc["r"], acc["l"], right, i).alias("r"))
        return F.when(i % 2 == 0, left_turn).otherwise(right_turn)

    order = range(ROUNDS - 1, -1, -1) if undo else range(ROUNDS)
    start = F.struct(F.expr("0L").alias("l"), F.expr("0L").alias("r"))
    seed = F.struct(F.floor(index / right).cast("long").alias("l"), F.pmod(index, right).cast("long").alias("r"))
    return F.aggregate(F.array(*map(F.lit, order)), F.coalesce(seed, start), step, lambda a: a["l"] * right + a["r"])


def _long(x: int) -> Column:
    return F.lit(x).cast("long")


def _num(text: Column, start: int, length: int) -> Column:
    return F.substr(text, F.lit(start), F.lit(length)).cast("long")


def _pad(x: Column, n: int) -> Column:
    return F.lpad(x.cast("string"), n, "0")


def luhn_sum(digits: Column, double_last: bool) -> Column:
    """Weighted digit sum; ``double_last`` doubles the last digit and every other before it."""
    n = F.length(digits)
    each = F.transform(
        F.sequence(F.lit(1), n),
        lambda p: F.when(
            F.pmod(n - p, F.lit(2)) == (0 if double_last else 1),
            F.lit("0246813579").substr(F.substr(digits, p, F.lit(1)).cast("int") + 1, F.lit(1)).cast("int"),
        ).otherwise(F.substr(digits, p, F.lit(1)).cast("int")),
    )
    return F.aggregate(each, F.lit(0), lambda a, x: a + x)


def _card(m: Column, key: str, undo: bool) -> Column:
    """First digit kept, the middle permuted, the check digit made anew."""
    digits = F.regexp_replace(m, "[^0-9]", "")
    n = F.length(digits)
    middle = n - 2
    right_len = F.ceil(middle / 2)
    power = [_long(10**k) for k in range(10)]

    def ten(k: Column) -> Column:
        return F.element_at(F.array(*power), (k + 1).cast("int"))

    index = F.substr(digits, F.lit(2), middle).cast("long")
    body = permute(index, ten(middle - right_len), ten(right_len), "card", key, undo)
    part = F.concat(F.substr(digits, F.lit(1), F.lit(1)), F.lpad(body.cast("string"), middle, F.lit("0")))
    check = F.pmod(10 - F.pmod(luhn_sum(part, True), F.lit(10)), F.lit(10))
    whole = F.concat(part, check.cast("string"))
    sep = F.regexp_extract(m, "[^0-9]", 0)
    spaced = F.concat_ws("", *[x for k in range(4) for x in ([sep] if k else []) + [F.substr(whole, F.lit(4 * k + 1), F.lit(4))]])
    valid = F.pmod(luhn_sum(digits, False), F.lit(10)) == 0
    return F.when(valid, F.when(F.length(sep) > 0, spaced).otherwise(whole)).otherwise(m)


def _ip(m: Column, key: str, undo: bool) -> Column:
    parts = F.split(m, r"\.")
    octets = [F.element_at(parts, k).cast("long") for k in (1, 2, 3, 4)]
    valid = F.array_max(F.array(*octets)) <= 255
    index = sum((o * _long(256 ** (3 - k)) for k, o in enumerate(octets)), _long(0))
    p = permute(index, _long(IP.left), _long(IP.right), "ip", key, undo)
    out = F.aggregate(
        F.array(p), F.lit(""), lambda a, x: F.concat_ws(".", *[F.shiftright(x, 8 * (3 - k)).bitwiseAND(_long(255)).cast("string") for k in range(4)])
    )
    return F.when(valid, out).otherwise(m)


def _phone(m: Column, key: str, undo: bool) -> Column:
    digits = F.regexp_replace(m, "[^0-9]", "")
    ten = F.substr(digits, F.length(digits) - 9, F.lit(10))
    index = ((_num(ten, 1, 3) - 200) * 800 + _num(ten, 4, 3) - 200) * 10_000 + _num(ten, 7, 4)
    p = permute(index, _long(PHONE.left), _long(PHONE.right), "phone", key, undo)

    def lay(x: Column) -> Column:
        area = _pad(F.floor(x / 8_000_000) + 200, 3)
        office = _pad(F.pmod(F.floor(x / 10_000), _long(800)) + 200, 3)
        groups = F.concat_ws("|", area, office, _pad(F.pmod(x, _long(10_000)), 4))
        mask = F.regexp_extract(m, r"^(.*?)[0-9]{3}([^0-9]+)[0-9]{3}([^0-9]+)[0-9]{4}$", 1)
        return F.concat(
            mask,
            F.split_part(groups, F.lit("|"), F.lit(1)),
            F.regexp_extract(m, r"[0-9]{3}([^0-9]+)[0-9]{3}[^0-9]+[0-9]{4}$", 1),
            F.split_part(groups, F.lit("|"), F.lit(2)),
            F.regexp_extract(m, r"[0-9]{3}([^0-9]+)[0-9]{4}$", 1),
            F.split_part(groups, F.lit("|"), F.lit(3)),
        )

    return F.aggregate(F.array(p), F.lit(""), lambda a, x: lay(x))


def _ssn(m: Column, key: str, undo: bool) -> Column:
    area, group, serial = _num(m, 1, 3), _num(m, 5, 2), _num(m, 8, 4)
    valid = (area > 0) & (area != 666) & (area < 900) & (group > 0) & (serial > 0)
    rank = F.when(area > 666, area - 2).otherwise(area - 1)
    p = permute((rank * 99 + group - 1) * 9_999 + serial - 1, _long(SSN.left), _long(SSN.right), "ssn", key, undo)

    def lay(x: Column) -> Column:
        a = F.floor(x / (99 * 9_999))
        return F.concat_ws(
            "-",
            _pad(F.when(a >= 665, a + 2).otherwise(a + 1), 3),
            _pad(F.pmod(F.floor(x / 9_999), _long(99)) + 1, 2),
            _pad(F.pmod(x, _long(9_999)) + 1, 4),
        )

    return F.when(valid, F.aggregate(F.array(p), F.lit(""), lambda a, x: lay(x))).otherwise(m)


def _date(m: Column, key: str, undo: bool) -> Column:
    day = F.try_to_date(m, "yyyy-MM-dd")
    index = F.datediff(day, F.lit(FIRST_DAY).cast("date")).cast("long")
    p = permute(index, _long(DATE.left), _long(DATE.right), "date", key, undo)
    out = F.date_format(F.date_add(F.lit(FIRST_DAY).cast("date"), p.cast("int")), "yyyy-MM-dd")
    return F.when(day.isNotNull(), out).otherwise(m)


def _tag(value: Column, key: str, n: int) -> Column:
    return F.substr(F.sha2(F.concat_ws("|", F.lit(key), F.lit("tag"), value), 256), F.lit(1), F.lit(n))


def pseudonym(m: Column, key: str) -> Column:
    """The replacement of one find."""

    def kind(name: str) -> Column:
        return m.rlike(f"^(?:{PATTERNS[name]})$")

    lower = F.lower(m)
    mail = F.concat(F.lit("u"), _tag(lower, key, 24), F.lit("@"), F.lit("mail.invalid"))
    access = F.concat(F.substr(m, F.lit(1), F.lit(4)), F.translate(_tag(m, key, 16), HEX, LETTERS))
    head = F.regexp_extract(m, r"^[^=:]*[=:]", 0)
    secret = F.concat(head, _tag(m, key, 18))
    before, quote = F.regexp_extract(m, r"^[^\"']*[\"']", 0), F.right(m, F.lit(1))
    token = F.concat(before, _tag(m, key, 40), quote)
    out = F.when(kind("mail"), mail).when(kind("access_key"), access).when(kind("token"), token).when(kind("password"), secret)
    return out.otherwise(_numbers(m, key, False))


def _numbers(m: Column, key: str, undo: bool) -> Column:
    def kind(name: str) -> Column:
        return m.rlike(f"^(?:{PATTERNS[name]})$")

    out = F.when(kind("ip"), _ip(m, key, undo)).when(kind("phone"), _phone(m, key, undo)).when(kind("ssn"), _ssn(m, key, undo))
    return out.when(kind("date"), _date(m, key, undo)).when(kind("card"), _card(m, key, undo)).otherwise(m)


def _rewrite(text: Column, change) -> Column:
    """The text with each find replaced: pieces between finds and changed finds, alternately."""
    finds = F.regexp_extract_all(text, F.lit(ANY), F.lit(0))
    pieces = F.split(text, ANY, -1)
    joined = F.array_join(F.zip_with(pieces, F.transform(finds, change), lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
    return F.when(text.rlike(HINT) & text.rlike(ANY), joined).otherwise(text)


def pseudonymize(docs: DataFrame, key: str = DEFAULT_KEY, text: str = "text") -> DataFrame:
    """The documents with every find replaced; columns as they came."""
    return docs.withColumn(text, _rewrite(F.col(text), lambda m: pseudonym(m, key)))


def reveal(docs: DataFrame, key: str = DEFAULT_KEY, text: str = "text") -> DataFrame:
    """Undo the permutations of numbers and dates; digests of mail addresses and secrets stay."""
    return docs.withColumn(text, _rewrite(F.col(text), lambda m: _numbers(m, key, True)))


def count_finds(text: Column) -> Column:
    """Number of finds in a text, as long; null gives 0."""
    n = F.when(text.rlike(HINT), F.size(F.regexp_extract_all(text, F.lit(ANY), F.lit(0)))).otherwise(0)
    return F.coalesce(n, F.lit(0)).cast("long")
