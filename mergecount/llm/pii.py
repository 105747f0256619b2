"""Format-preserving Feistel pseudonyms for personal data, with built-in SQL functions only.

Every kind is found by one pattern, checked (Luhn, mod 97, calendar, octet and area ranges) and
replaced by a keyed permutation inside its own format, so equal values get equal pseudonyms in
every document, distinct values stay distinct, and a pseudonym passes the same check:

* card numbers: all digits but the last are permuted, the Luhn digit is computed anew;
* account numbers (IBAN): the account part is permuted, the mod-97 digits are computed anew;
* dates of 1700 to 2099 (one Gregorian cycle): days up to the 12th of a month and days after it are
  permuted apart (240 x 240 and 9 x 9833 days), so a date that reads as day first, month first or either
  keeps that reading and no two dates share a pseudonym in any spelling; 2024-02-29, 2024/02/29,
  29/02/2024 and the date of a timestamp are one day with one pseudonym;
* IPv4 addresses: permuted over 65536 x 65536, leading zeros kept; US social numbers over 88902 x 9999;
* phone numbers: digits after the country code; e-mail local parts and the value of credentials
  (token, secret, password, key, access key ids), of any length: letters stay letters, digits stay
  digits, other signs stay; hexadecimal values stay hexadecimal and others stay others.

Each is a Feistel network of ``ROUNDS`` rounds whose round function is SHA-2 of key, kind, round, block
and the other half. The key has no default: pass it from a secret store (queries read
``spark.mergecount.pii.key``). It is a literal of the plan, so keep event logs private. All work is inside
a row: no shuffle, no Python, any skew is harmless. Times of day, domains of e-mail addresses and country
codes stay.

Edge cases: null text stays null; empty and very long texts are treated whole; candidates that
fail their check stay as they are; repeated rows get equal results; other columns are kept,
whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

ROUNDS = 8
#: Where queries find the key, and the key of runs whose session has none (tests, demonstrations).
KEY_SETTING, DEMO_KEY = "spark.mergecount.pii.key", "demonstration only"
CYCLE_START, CYCLE_DAYS, MONTHS = "1700-01-01", 146097, 4800
#: Factors of the days up to the 12th (12 * 4800) and after it (146097 - 12 * 4800), rounds for the second.
EARLY, LATE, LATE_ROUNDS = (240, 240), (9, 9833), 24

_SIGNS = r"0-9A-Za-z_+/~.\-"
EMAIL = r"(?<![A-Za-z0-9._%+\-])[A-Za-z0-9._%+\-]++@[A-Za-z0-9.\-]+\.[A-Za-z]{2,24}(?![A-Za-z0-9])"
WORD = r"(?i:token|secret|password|passwd|api_?key)\s{0,3}[=:]"
VALUE = rf"(?:(?=[A-Za-z_+/~.\-]*[0-9])[{_SIGNS}]{{8,}}|[{_SIGNS}]{{12,}})={{0,2}}"
SECRET = rf"(?:{WORD}\s{{0,3}}[\"']?{VALUE}|(?<![0-9A-Za-z])AKIA[0-9A-Z]{{16}}(?![0-9A-Za-z]))"
STAMP = r"(?<![0-9A-Za-z])(?<![0-9][.\-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?=T[0-9]{2})"
DATES = (r"[0-9]{4}-[0-9]{2}-[0-9]{2}", r"[0-9]{4}/[0-9]{2}/[0-9]{2}", r"[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}", r"[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4}")
NUMBERS = (
    r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?",
    *DATES,
    r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}",
    r"[0-9]{3}-[0-9]{2}-[0-9]{4}",
    r"\+[0-9]{1,3} ?\([0-9]{1,4}\) ?[0-9]{3}[ \-][0-9]{4}",
    r"\+[0-9]{1,3}(?:[ .\-]?[0-9]{2,4}){2,5}",
    r"\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}",
    r"[0-9]{4}(?: [0-9]{4}){2} [0-9]{1,7}",
    r"[0-9]{4}(?:-[0-9]{4}){2}-[0-9]{1,7}",
    r"[0-9]{4}[ \-][0-9]{6}[ \-][0-9]{5}",
    r"[0-9]{13,19}",
)
PATTERN = EMAIL + "|" + SECRET + "|" + STAMP + r"|(?<![0-9A-Za-z])(?<![0-9][.\-])(?:" + "|".join(NUMBERS) + r")(?![0-9A-Za-z])(?![.\-][0-9])"
#: What every match of PATTERN has.
ANY = "[0-9@]|AKIA|" + WORD


def key_of(spark: SparkSession) -> str:
    """The session's key; without one a fixed key that hides nothing from its readers."""
    return spark.conf.get(KEY_SETTING, None) or DEMO_KEY


def _num(text: Column) -> Column:
    return F.coalesce(F.when(text == "", F.lit("0")).otherwise(text).try_cast("long"), F.lit(0).cast("long"))


def _only(text: Column, keep: str) -> Column:
    return F.regexp_replace(text, f"[^{keep}]", "")


def _round_hash(key: str, kind: str, i: Column, block: Column, half: Column) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), F.lit(kind), i.cast("string"), block.cast("string"), half).cast("binary"), 512)


def permute_number(n: Column, a: int, b: int, key: str, kind: str, count: int = ROUNDS) -> Column:
    """Keyed permutation of 0..a*b-1: additions modulo a and b by turns."""

    def step(acc: Column, i: Column) -> Column:
        def add(to: Column, other: Column, size: int) -> Column:
            h = F.conv(F.substring(_round_hash(key, kind, i, F.lit(0), other.cast("string")), 1, 14), 16, 10).cast("long")
            return F.pmod(to + h, F.lit(size).cast("long"))

        even = i % 2 == 0
        return F.struct(F.when(even, add(acc["l"], acc["r"], a)).otherwise(acc["l"]).alias("l"), F.when(even, acc["r"]).otherwise(add(acc["r"], acc["l"], b)).alias("r"))

    begin = F.struct(F.floor(n / b).cast("long").alias("l"), F.pmod(n, F.lit(b).cast("long")).alias("r"))
    rounds = F.array(*[F.lit(i) for i in range(count)])
    return F.aggregate(rounds, begin, step, lambda acc: acc["l"] * b + acc["r"])


def permute_symbols(text: Column, key: str, kind: str, pivot: Column | None = None) -> Column:
    """Keyed permutation of strings of lower-case letters and digits that keeps the class of every place.

    With ``pivot`` (the place of the first letter after f, the length if there is none) letters before it
    stay within a to f and the letter there within g to z, so the pivot itself is kept.
    """

    def shifted(half: Column, i: Column, other: Column, offset: Column) -> Column:
        blocks = F.sequence(F.lit(0), F.floor((F.length(half) - 1) / 42).cast("int"))  # a digest serves 42 places
        digests = F.transform(blocks, lambda block: _round_hash(key, kind, i, block, other))

        def one(c: Column, j: Column, digest: Column) -> Column:
            k = F.conv(F.substring(F.get(digest, F.floor(j / 42).cast("int")), F.pmod(j, F.lit(42)) * 3 + 1, F.lit(3)), 16, 10).cast("int")
            at = j + offset
            first, size = F.lit(97), F.lit(26)
            if pivot is not None:
                first, size = F.when(at == pivot, 103).otherwise(97), F.when(at < pivot, 6).when(at == pivot, 20).otherwise(26)
            digit = c.between("0", "9")
            first, size = F.when(digit, 48).otherwise(first), F.when(digit, 10).otherwise(size)
            return F.char(first + F.pmod(F.ascii(c) - first + k, size))

        turned = C.once(digests, lambda d: F.array_join(F.transform(F.split(half, ""), lambda c, j: one(c, j, d)), ""))
        return F.when(half == "", half).otherwise(turned)

    cut = F.floor(F.length(text) / 2).cast("int")

    def step(acc: Column, i: Column) -> Column:
        even = i % 2 == 0
        left = F.when(even, shifted(acc["l"], i, acc["r"], F.lit(0))).otherwise(acc["l"])
        right = F.when(even, acc["r"]).otherwise(shifted(acc["r"], i, acc["l"], cut))
        return F.struct(left.alias("l"), right.alias("r"))

    begin = F.struct(F.substring(text, F.lit(1), cut).alias("l"), F.substring(text, cut + 1, F.length(text)).alias("r"))
    return F.aggregate(F.array(*[F.lit(i) for i in range(ROUNDS)]), begin, step, lambda acc: F.concat(acc["l"], acc["r"]))


def laid_out(like: Column, symbols: Column) -> Column:
    """``symbols`` in the separators and letter case of ``like``."""
    between = F.split(like, "[0-9A-Za-z]", -1)
    cased = F.zip_with(F.regexp_extract_all(like, F.lit("[0-9A-Za-z]"), F.lit(0)), F.split(symbols, ""), lambda old, new: F.when(old.between("A", "Z"), F.upper(new)).otherwise(new))
    return F.when(symbols == "", like).otherwise(F.array_join(F.zip_with(between, cased, lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), ""))


def _hidden(part: Column, key: str, kind: str, pivot=None) -> Column:
    return laid_out(part, C.once(F.lower(_only(part, "0-9A-Za-z")), lambda x: permute_symbols(x, key, kind, None if pivot is None else pivot(x))))


def luhn_digit(payload: Column) -> Column:
    """Check digit that makes payload + digit pass."""
    places = F.split(F.reverse(payload), "")
    doubled = lambda c, j: F.when(j % 2 == 0, c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0)).otherwise(c.cast("int"))
    total = F.aggregate(F.transform(places, doubled), F.lit(0), lambda acc, x: acc + x)
    return F.pmod(10 - total % 10, F.lit(10)).cast("string")


def mod97(text: Column) -> Column:
    """Remainder of the number that the characters spell (A is 10, Z is 35)."""
    def add(acc: Column, c: Column) -> Column:
        return F.when(c.between("0", "9"), (acc * 10 + F.ascii(c) - 48) % 97).otherwise((acc * 100 + F.ascii(c) - 55) % 97)

    return F.aggregate(F.split(text, ""), F.lit(0), add)


def _card(hit: Column, key: str) -> Column:
    digits = _only(hit, "0-9")
    n = F.length(digits)
    payload = F.substring(digits, F.lit(1), n - 1)
    new = permute_symbols(payload, key, "card")
    return F.when((n >= 13) & (n <= 19) & (luhn_digit(payload) == F.substring(digits, n, F.lit(1))), laid_out(hit, F.concat(new, luhn_digit(new)))).otherwise(hit)


def _iban(hit: Column, key: str) -> Column:
    whole = F.regexp_replace(hit, " ", "")
    account = F.substring(whole, F.lit(5), F.length(whole))
    new = F.upper(permute_symbols(F.lower(account), key, "iban"))
    land = F.substring(whole, 1, 2)
    check = F.lpad((98 - mod97(F.concat(new, land, F.lit("00")))).cast("string"), 2, "0")
    good = F.length(whole).between(15, 34) & (mod97(F.concat(account, F.substring(whole, 1, 4))) == 1)
    return F.when(good, laid_out(hit, F.concat(F.lower(land), check, F.lower(new)))).otherwise(hit)


def _permuted_day(day: Column, key: str) -> Column:
    start = F.lit(CYCLE_START).cast("date")
    n = F.datediff(day, start).cast("long")
    month = ((F.year(day) - 1700) * 12 + F.month(day) - 1).cast("long")
    early = F.dayofmonth(day) <= 12
    new = permute_number(month * 12 + F.dayofmonth(day) - 1, *EARLY, key, "early-date")
    early_day = C.once(new, lambda x: F.date_add(F.add_months(start, F.floor(x / 12).cast("int")), F.pmod(x, F.lit(12)).cast("int")))

    # Late days are numbered through; the month of a number is near its share of all months.
    base = lambda m: F.datediff(F.add_months(start, m.cast("int")), start) - m * 12

    def late_day(x: Column) -> Column:
        guess = F.floor(x * MONTHS / (CYCLE_DAYS - 12 * MONTHS))
        found = F.when(base(guess + 1) <= x, guess + 1).when(base(guess) <= x, guess).otherwise(guess - 1)
        return F.date_add(F.add_months(start, found.cast("int")), (x - base(found) + 12).cast("int"))

    late = C.once(permute_number(n - (month + 1) * 12, *LATE, key, "late-date", LATE_ROUNDS), late_day)
    return F.when(early, early_day).otherwise(late)


def _date(hit: Column, key: str) -> Column:
    year_first = hit.rlike("^[0-9]{4}[-/]")
    parts = F.split(hit, "[-./]")
    spelled = lambda y, m, d: F.try_to_date(F.concat(parts[y], F.lit("-"), F.lpad(parts[m], 2, "0"), F.lit("-"), F.lpad(parts[d], 2, "0")), "yyyy-MM-dd")
    day_first = F.when(~year_first, F.when(~year_first, spelled(2, 1, 0)))
    month_first = F.when(~year_first, spelled(2, 0, 1))
    day = F.when(year_first, spelled(0, 1, 2)).otherwise(F.coalesce(day_first, month_first))
    known = day.between(F.lit(CYCLE_START).cast("date"), F.lit("2099-12-31").cast("date"))
    dot, padded = hit.contains("."), hit.rlike("^[0-9]{2}[./][0-9]{2}[./]")

    def written(new: Column) -> Column:
        by = lambda fmt: F.date_format(new, fmt)
        local = F.when(day_first.isNotNull(), F.when(padded, by("dd/MM/yyyy")).otherwise(by("d/M/yyyy"))).otherwise(F.when(padded, by("MM/dd/yyyy")).otherwise(by("M/d/yyyy")))
        return F.when(year_first, F.when(hit.contains("-"), by("yyyy-MM-dd")).otherwise(by("yyyy/MM/dd"))).when(dot, F.regexp_replace(local, "/", ".")).otherwise(local)

    return F.when(known, C.once(_permuted_day(day, key), written)).otherwise(hit)


def _ip(hit: Column, key: str) -> Column:
    parts = F.split(hit, r"\.")
    octets = F.transform(parts, lambda x: x.cast("long"))
    n = F.aggregate(octets, F.lit(0).cast("long"), lambda acc, x: acc * 256 + x)

    def spelled(new: Column) -> Column:
        one = lambda part, x: F.when((F.length(part) > F.length(x)) & part.startswith("0"), F.lpad(x, F.length(part), F.lit("0"))).otherwise(x)
        return F.concat_ws(".", *[one(parts[i], F.pmod(F.shiftright(new, 24 - 8 * i), F.lit(256)).cast("string")) for i in range(4)])

    return F.when(F.forall(octets, lambda x: x <= 255), C.once(permute_number(n, 65536, 65536, key, "ip"), spelled)).otherwise(hit)


def _social(hit: Column, key: str) -> Column:
    area, group, serial = (_num(F.substring(hit, at, size)) for at, size in ((1, 3), (5, 2), (8, 4)))
    good = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    place = area - F.when(area > 666, 2).otherwise(1)
    new = permute_number(((place * 99) + group - 1) * 9999 + serial - 1, 88902, 9999, key, "social")
    serial2, rest = F.pmod(new, F.lit(9999)) + 1, F.floor(new / 9999)
    group2, place2 = F.pmod(rest, F.lit(99)) + 1, F.floor(rest / 99)
    area2 = place2 + F.when(place2 >= 665, 2).otherwise(1)
    return F.when(good, F.concat_ws("-", *[F.lpad(x.cast("string"), w, "0") for x, w in ((area2, 3), (group2, 2), (serial2, 4))])).otherwise(hit)


def _phone(hit: Column, key: str) -> Column:
    head = F.regexp_extract(hit, r"^(\+[0-9]{1,3}(?=[ .\-(])|\+[0-9])?", 0)
    rest = F.substring(hit, F.length(head) + 1, F.length(hit))
    return F.when(F.length(_only(hit, "0-9")).between(7, 15), F.concat(head, _hidden(rest, key, "phone"))).otherwise(hit)


def _email(hit: Column, key: str) -> Column:
    at = F.locate("@", hit)
    return F.concat(_hidden(F.substring(hit, F.lit(1), at - 1), key, "email"), F.substring(hit, at, F.length(hit)))


def _secret(hit: Column, key: str) -> Column:
    head = F.regexp_extract(hit, "^(AKIA(?=[0-9A-Z]{16}$)|[^=:]*[=:]\\s{0,3}[\"']?)", 0)
    value = F.substring(hit, F.length(head) + 1, F.length(hit))
    return F.concat(head, _hidden(value, key, "secret", lambda x: F.length(F.regexp_extract(x, "^[0-9a-f]*", 0))))


def pseudonym(hit: Column, key: str) -> Column:
    """The pseudonym of one candidate, or the candidate itself if it fails its check."""
    digit_start = hit.rlike("^[0-9]")
    return (
        F.when(hit.rlike("^(?:AKIA[0-9A-Z]{16}$|[A-Za-z_]+\\s{0,3}[=:])"), _secret(hit, key))
        .when(hit.contains("@"), _email(hit, key))
        .when(hit.rlike("^[A-Z]"), _iban(hit, key))
        .when(hit.rlike("^[+(]"), _phone(hit, key))
        .when(digit_start & hit.rlike("^(?:" + "|".join(DATES) + ")$"), _date(hit, key))
        .when(digit_start & hit.rlike(r"^[0-9]{1,3}(?:\.[0-9]{1,3}){3}$"), _ip(hit, key))
        .when(digit_start & hit.rlike("^[0-9]{3}-[0-9]{2}-[0-9]{4}$"), _social(hit, key))
        .otherwise(_card(hit, key))
    )


def pseudonymize(docs: DataFrame, key: str, column: str = "text", found: str | None = None) -> DataFrame:
    """``docs`` with ``column`` rewritten under ``key``; ``found`` names a column for the number of replaced values, if asked for."""
    if not key:
        raise ValueError("a key is needed: pass it from a secret store")
    kept = docs.columns
    quote = lambda c: F.col(f"`{c}`")
    text = quote(column)
    some = text.rlike(ANY)
    cut = docs.select(
        F.struct(*[quote(c) for c in kept]).alias("in"),
        F.when(some, F.split(text, PATTERN, -1)).alias("parts"),
        F.when(some, F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).alias("hits"),
    )
    new = cut.withColumn("new", F.transform("hits", lambda h: pseudonym(h, key)))
    merged = F.array_join(F.flatten(F.zip_with("parts", "new", lambda a, b: F.array(a, F.coalesce(b, F.lit(""))))), "")
    old = lambda c: F.col(f"in.`{c}`")
    out = F.when(F.coalesce(F.size("hits"), F.lit(0)) > 0, merged).otherwise(old(column))
    changed = F.aggregate(F.zip_with("hits", "new", lambda a, b: F.when(a != b, 1).otherwise(0)), F.lit(0), lambda acc, x: acc + x)
    columns = [(out if c == column else old(c)).alias(c) for c in kept]
    return new.select(*columns, *([F.coalesce(changed, F.lit(0)).alias(found)] if found else []))


def op1_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's id, whole pseudonymized text and number of replaced values."""
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    return pseudonymize(docs, key_of(spark), found="replaced")
