"""PII: format-preserving Feistel pseudonyms, in native SQL.

Found and validated values are replaced by keyed permutations within their own format, so equal values
get equal pseudonyms in every document, different values different ones, and a holder of the key can
undo it (``inverse=True``):

* card numbers (13 to 19 digits, valid check digit): the payload is permuted, the check digit made anew;
* IBANs (valid mod-97 remainder): country kept, the rest permuted, check digits made anew;
* dates (ISO, or day.month.year and day/month/year; real days from 1900 to 2099): permuted among those days;
* US social security numbers (valid area, group and serial): permuted among valid ones;
* IPv4 addresses (octets up to 255), phone numbers in international form (country code kept), the local
  part of e-mail addresses, and hexadecimal secrets of 32 to 64 characters: permuted by character class.

Numbers that fail their validation stay. Cards are sought in a whole run of digit groups: the run itself, else
every part of it that begins and ends with a group (those before the last of three digits or more), so a year,
expiry or code beside a card does not hide it. In such runs, about one pseudonym in ten makes a longer or earlier
part valid too, and ``inverse`` then reads another part than was written. IBANs end where those of their country do.

Two networks are used. Digits and letters: a balanced Feistel over the two halves of a string, in which each
character is shifted within its class by a keyed hash of the other half. Number pairs: the same over Z_a x Z_b,
which needs no cycle walking as a * b is the domain.

A text is split into literal pieces and matches; only texts with a match are touched. Null texts stay null,
empty texts empty; separators and lengths inside a value stay, but for IPv4 octets. All columns stay, repeated
rows too.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm.store import fresh, table

#: Used only where the session has no key of its own under ``KEY_SETTING``; anyone who reads this can invert it.
KEY = "ripple-pseudonyms-1"
KEY_SETTING = "spark.ripplegraph.pii.key"
ROUNDS = 8

#: Characters of an IBAN by country.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK FI FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA", 23: "AE GI IL IQ",
    24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB PL SV", 29: "BR EG PS QA UA", 30: "JO KW MU", 31: "MT SC", 32: "LC",
}


def _iban_of(length: int, countries: str) -> str:
    groups, rest = divmod(length - 4, 4)
    return rf"(?:{countries.replace(' ', '|')})\d{{2}}(?: ?[0-9A-Z]{{4}}){{{groups}}}" + (rf" ?[0-9A-Z]{{{rest}}}" if rest else "")


#: Alternatives in order of precedence. Each starts at a boundary, so a scan is linear in the text.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "hex": r"(?<![0-9A-Za-z])(?:[0-9a-f]{32,64}|[0-9A-F]{32,64})(?![0-9A-Za-z])",
    "iban": rf"(?<![0-9A-Za-z])(?:{'|'.join(_iban_of(n, c) for n, c in IBAN_LENGTHS.items())}|[A-Z]{{2}}\d{{2}}(?: ?[0-9A-Z]{{4}}){{2,7}}(?: ?[0-9A-Z]{{1,3}})?)(?![0-9A-Za-z])",
    "phone": r"\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){1,3}(?!\d|[.]\d)",
    "date": r"(?<![\d./-])(?:\d{4}-\d{2}-\d{2}|\d{2}/\d{2}/\d{4}|\d{2}\.\d{2}\.\d{4})(?![\d/-])",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "ip": r"(?<![\d.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?!\d|\.\d)",
}
#: A whole run of digit groups, in which cards are sought; it ends where another kind of value begins.
PATTERNS["card"] = rf"(?<!\d)\d(?:(?:[ -](?!{'|'.join(PATTERNS[k] for k in ('email', 'date', 'ssn', 'ip'))}))?\d){{12,}}+"
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: What every match has; texts without it are passed over in one quick scan.
HINT = r"[0-9@]|[a-fA-F]{32}"
#: 73,049 days from 1900-01-01 to 2099-12-31.
_DAYS = (319, 229)
#: Valid areas (001 to 899 without 666), groups times serials.
_SSN = (898, 99 * 9999)


def _bound(value: Column, then) -> Column:
    """``then`` of a value that is computed once."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def _order(inverse: bool) -> Column:
    return F.sequence(F.lit(ROUNDS - 1), F.lit(0)) if inverse else F.sequence(F.lit(0), F.lit(ROUNDS - 1))


def feistel_text(value: Column, kind: str, letters: int = 26, key: str = KEY, inverse: bool = False) -> Column:
    """Permute a string of ASCII letters and digits within the class of each character."""
    sign = -1 if inverse else 1

    def shift(own: Column, other: Column, r: Column) -> Column:
        seed = F.concat_ws("|", F.lit(f"{key}|{kind}"), F.length(own), r, other)
        pad = F.concat(F.sha2(F.concat(seed, F.lit("|a")), 512), F.sha2(F.concat(seed, F.lit("|b")), 512))

        def moved(pad: Column, j: Column) -> Column:
            c = F.ascii(F.substr(own, j, F.lit(1)))
            by = F.conv(F.substr(pad, F.pmod(j - 1, F.lit(64)) * 4 + 1, F.lit(4)), 16, 10).cast("int") * sign
            turn = lambda base, n: F.pmod(c - base + by, F.lit(n)) + base
            return F.char(F.when(c < 58, turn(48, 10)).when(c < 91, turn(65, letters)).otherwise(turn(97, letters)))

        return F.when(F.length(own) == 0, own).otherwise(_bound(pad, lambda p: F.array_join(F.transform(F.sequence(F.lit(1), F.length(own)), lambda j: moved(p, j)), "")))

    half = (F.length(value) / 2).cast("int")
    start = F.struct(F.substr(value, F.lit(1), half).alias("a"), F.substr(value, half + 1, F.length(value)).alias("b"))

    def turned(s: Column, r: Column) -> Column:
        even = r % 2 == 0
        return F.struct(F.when(even, shift(s["a"], s["b"], r)).otherwise(s["a"]).alias("a"), F.when(even, s["b"]).otherwise(shift(s["b"], s["a"], r)).alias("b"))

    return F.aggregate(_order(inverse), start, turned, lambda s: F.concat(s["a"], s["b"]))


def feistel_pair(x: Column, y: Column, a: int, b: int, kind: str, key: str = KEY, inverse: bool = False) -> Column:
    """Permute (x, y) in Z_a x Z_b; a struct with fields x and y."""
    sign = -1 if inverse else 1

    def turned(s: Column, r: Column) -> Column:
        def by(other: Column) -> Column:
            return F.conv(F.substring(F.sha2(F.concat_ws("|", F.lit(f"{key}|{kind}"), r, other), 256), 1, 12), 16, 10).cast("long") * sign

        even = r % 2 == 0
        return F.struct(F.when(even, F.pmod(s["x"] + by(s["y"]), F.lit(a))).otherwise(s["x"]).alias("x"), F.when(even, s["y"]).otherwise(F.pmod(s["y"] + by(s["x"]), F.lit(b))).alias("y"))

    return F.aggregate(_order(inverse), F.struct(x.cast("long").alias("x"), y.cast("long").alias("y")), turned)


def _into(template: Column, chars: Column, which: str) -> Column:
    """Put ``chars`` one by one in the places of ``template`` that are of class ``which``."""
    upto = lambda i: F.length(F.regexp_replace(F.substr(template, F.lit(1), i), f"[^{which}]", ""))
    one = lambda i: F.substr(template, i, F.lit(1))
    return F.array_join(F.transform(F.sequence(F.lit(1), F.length(template)), lambda i: F.when(one(i).rlike(f"^[{which}]$"), F.substr(chars, upto(i), F.lit(1))).otherwise(one(i))), "")


def _only(value: Column, which: str) -> Column:
    return F.regexp_replace(value, f"[^{which}]", "")


def luhn_sum(digits: Column) -> Column:
    """Sum of a number whose check digit is its last one."""
    n = F.length(digits)
    one = lambda i: F.substr(digits, i, F.lit(1)).cast("int")
    twice = lambda d: F.when(d > 4, d * 2 - 9).otherwise(d * 2)
    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda s, i: s + F.when((n - i) % 2 == 1, twice(one(i))).otherwise(one(i)))


def iban_remainder(plain: Column) -> Column:
    turned = F.concat(F.substr(plain, F.lit(5), F.length(plain)), F.substring(plain, 1, 4))
    code = lambda c: F.when(F.ascii(c) < 58, F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    return F.aggregate(F.split(turned, ""), F.lit(0), lambda s, c: F.when(c == "", s).otherwise((s * F.when(F.ascii(c) < 58, 10).otherwise(100) + code(c)) % 97))


def _is_card(v: Column) -> Column:
    digits = _only(v, "0-9")
    return F.when(F.length(digits).between(13, 19), luhn_sum(digits) % 10 == 0).otherwise(F.lit(False))


def _one_card(v: Column, key: str, inverse: bool) -> Column:
    digits = _only(v, "0-9")
    payload = feistel_text(F.substr(digits, F.lit(1), F.length(digits) - 1), "card", 26, key, inverse)
    checked = _bound(payload, lambda p: F.concat(p, F.pmod(-luhn_sum(F.concat(p, F.lit("0"))), F.lit(10)).cast("string")))
    return _bound(checked, lambda d: _into(v, d, "0-9"))


def _card(v: Column, key: str, inverse: bool) -> Column:
    """The whole run if it is a card; else from the left the longest card that begins at each group and ends with one."""

    def cards(groups: Column) -> Column:
        span = lambda i, n: F.array_join(F.slice(groups, i, n), "")

        def moved(s: Column, i: Column) -> Column:
            lengths = F.sequence(F.least(F.size(groups) - i + 1, F.lit(19)), F.lit(1), F.lit(-1))
            longest = F.get(F.filter(lengths, lambda n: span(i, n).rlike(r"^[ -]?(?:\d{3,}[ -])*\d+$") & _is_card(span(i, n))), F.lit(0))
            found = _bound(longest, lambda n: F.when(n.isNull(), F.struct(F.concat(s["out"], F.get(groups, i - 1)).alias("out"), (i + 1).alias("next"))).otherwise(F.struct(F.concat(s["out"], _one_card(span(i, n), key, inverse)).alias("out"), (i + n).alias("next"))))
            return F.when(i < s["next"], s).otherwise(found)

        return F.aggregate(F.sequence(F.lit(1), F.size(groups)), F.struct(F.lit("").alias("out"), F.lit(1).alias("next")), moved, lambda s: s["out"])

    return F.when(_is_card(v), _one_card(v, key, inverse)).when(v.rlike("[ -]"), _bound(F.regexp_extract_all(v, F.lit(r"[ -]?\d+"), F.lit(0)), cards)).otherwise(v)


def _iban(v: Column, key: str, inverse: bool) -> Column:
    plain = F.replace(v, F.lit(" "), F.lit(""))
    country = F.substring(plain, 1, 2)
    body = feistel_text(F.substr(plain, F.lit(5), F.length(plain)), "iban", 26, key, inverse)
    checked = _bound(body, lambda b: F.concat(country, F.lpad((F.lit(98) - iban_remainder(F.concat(country, F.lit("00"), b))).cast("string"), 2, "0"), b))
    return F.when(iban_remainder(plain) == 1, _bound(checked, lambda d: _into(v, d, "0-9A-Z"))).otherwise(v)


def _date(v: Column, key: str, inverse: bool) -> Column:
    mark = F.when(v.rlike(r"^\d{4}-"), F.lit("yyyy-MM-dd")).when(F.contains(v, F.lit("/")), F.lit("dd/MM/yyyy")).otherwise(F.lit("dd.MM.yyyy"))
    iso = F.when(v.rlike(r"^\d{4}-"), v).otherwise(F.concat_ws("-", F.substring(v, 7, 4), F.substring(v, 4, 2), F.substring(v, 1, 2)))
    day = F.datediff(iso.try_cast("date"), F.lit("1900-01-01").cast("date"))
    a, b = _DAYS
    moved = feistel_pair(F.floor(day / b), day % b, a, b, "date", key, inverse)
    out = _bound(moved, lambda s: F.date_add(F.lit("1900-01-01").cast("date"), (s["x"] * b + s["y"]).cast("int")))
    shown = _bound(out, lambda d: F.when(mark == "yyyy-MM-dd", F.date_format(d, "yyyy-MM-dd")).when(mark == "dd/MM/yyyy", F.date_format(d, "dd/MM/yyyy")).otherwise(F.date_format(d, "dd.MM.yyyy")))
    return F.when(day.between(0, a * b - 1), shown).otherwise(v)


def _ssn(v: Column, key: str, inverse: bool) -> Column:
    area, group, serial = (F.substr(v, F.lit(i), F.lit(n)).cast("int") for i, n in ((1, 3), (5, 2), (8, 4)))
    valid = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    a, b = _SSN
    moved = feistel_pair(F.when(area > 666, area - 2).otherwise(area - 1), (group - 1) * 9999 + serial - 1, a, b, "ssn", key, inverse)
    shown = _bound(moved, lambda s: F.format_string("%03d-%02d-%04d", F.when(s["x"] >= 665, s["x"] + 2).otherwise(s["x"] + 1), F.floor(s["y"] / 9999) + 1, s["y"] % 9999 + 1))
    return F.when(valid, shown).otherwise(v)


def _ip(v: Column, key: str, inverse: bool) -> Column:
    octet = lambda i: F.get(F.split(v, r"\."), F.lit(i)).cast("int")
    valid = F.greatest(*(octet(i) for i in range(4))) <= 255
    moved = feistel_pair(octet(0) * 256 + octet(1), octet(2) * 256 + octet(3), 65536, 65536, "ip", key, inverse)
    shown = _bound(moved, lambda s: F.concat_ws(".", F.floor(s["x"] / 256), s["x"] % 256, F.floor(s["y"] / 256), s["y"] % 256))
    return F.when(valid, shown).otherwise(v)


def _phone(v: Column, key: str, inverse: bool) -> Column:
    code = F.regexp_extract(v, r"^\+\d{1,3}(?=[ .(-])|^\+\d", 0)
    rest = F.substr(v, F.length(code) + 1, F.length(v))
    return F.concat(code, _bound(feistel_text(_only(rest, "0-9"), "phone", 26, key, inverse), lambda d: _into(rest, d, "0-9")))


def _email(v: Column, key: str, inverse: bool) -> Column:
    local, host = F.substring_index(v, "@", 1), F.regexp_extract(v, r"@.*$", 0)
    chars = _only(local, "0-9A-Za-z")
    return F.concat(F.when(F.length(chars) == 0, local).otherwise(_bound(feistel_text(chars, "email", 26, key, inverse), lambda d: _into(local, d, "0-9A-Za-z"))), host)


def pseudonym(v: Column, key: str = KEY, inverse: bool = False) -> Column:
    """The pseudonym of one match of ``ANY``."""
    is_ = lambda kind: v.rlike(f"^(?:{PATTERNS[kind]})$")
    return (
        F.when(F.contains(v, F.lit("@")), _email(v, key, inverse))
        .when(is_("hex"), feistel_text(v, "hex", 6, key, inverse))
        .when(is_("iban"), _iban(v, key, inverse))
        .when(F.startswith(v, F.lit("+")), _phone(v, key, inverse))
        .when(is_("date"), _date(v, key, inverse))
        .when(is_("ssn"), _ssn(v, key, inverse))
        .when(is_("ip"), _ip(v, key, inverse))
        .otherwise(_card(v, key, inverse))
    )


def pseudonymise(docs: DataFrame, text: str = "text", key: str | None = None, inverse: bool = False, count: str | None = "n_pseudonyms") -> DataFrame:
    """``docs`` with ``text`` pseudonymised and a column ``count`` of matches that changed (cards in one run are one).

    ``key`` None: the session's ``KEY_SETTING``, or else the known test key. A column of the name ``count`` is
    replaced; with ``count`` None none is added. All other columns stay, whatever their names.
    """
    key = docs.sparkSession.conf.get(KEY_SETTING, KEY) if key is None else key
    was, now = fresh(docs, "matches_found", "matches_new")
    own = F.col(text)
    found = docs.withColumn(was, F.when(own.rlike(HINT) & own.rlike(ANY), F.regexp_extract_all(own, F.lit(ANY), F.lit(0))))
    found = found.withColumn(now, F.transform(was, lambda v: pseudonym(v, key, inverse)))
    pieces = F.transform(F.split(own, ANY), lambda x, i: F.concat(x, F.coalesce(F.get(now, i), F.lit(""))))
    changed = F.size(F.filter(F.arrays_zip(was, now), lambda z: z[was] != z[now]))
    out = found.withColumn(text, F.when(F.col(was).isNull(), own).otherwise(F.array_join(pieces, "")))
    if count is not None:
        out = out.withColumn(count, F.coalesce(F.when(F.col(was).isNotNull(), changed), F.lit(0)).cast("long"))
    return out.drop(was, now)


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return pseudonymise(docs)
