"""Pseudonyms of personal data that keep their format, in DataFrame functions only.

Numbers and dates that pass the validation of their kind go through a keyed Feistel permutation of all values of
that format: a card number becomes another valid one, an address another address, a date another date. Equal
values become equal pseudonyms in every document, whatever their separators, and different ones different ones.
Numbers that fail validation are no personal data and stay: cards by their check digit, IBANs by their remainder, social
numbers by their parts, addresses by their octets, phone numbers by a country code and 7 to 14 digits after it. What
names an issuer or a country stays, so a pseudonym fits the pattern its value came by: the first six digits of a card,
the country of an IBAN, the country code of a phone number (a number in the form (123) 456-7890 counts as one of
country 1). Dates are days of the years 1 to 9999; with slashes they
are read day first, then month first, and written back in the order that holds.

Cases: a null text stays null; an empty one stays empty; a null or repeated id is kept; overlapping candidates
go to the leftmost, then to the kind listed first; a text of any length is read whole; an empty table gives an
empty result; `pseudonymised` keeps further columns, whatever they are called, as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 10
#: The kinds and their patterns, in order of preference. Possessive and bounded: linear in the text.
KINDS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "date": r"(?<![0-9.-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9-])|(?<![0-9./])[0-9]{2}[./][0-9]{2}[./][0-9]{4}(?![0-9])",
    "address": r"(?<![0-9])(?<![0-9]\.)[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9]|\.[0-9])",
    "phone": r"(?<![0-9+])\+[0-9]{1,3}[ .-]?(?:\([0-9]{2,4}\)|[0-9]{2,4})(?:[ .-]?[0-9]{2,4}){2,3}(?![0-9])|(?<![0-9+(])\([0-9]{3}\) ?[0-9]{3}[ .-][0-9]{4}(?![0-9])",
    "social": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "card": r"(?<![0-9])(?:[0-9]{13,19}|[0-9]{4}[ -][0-9]{4}[ -][0-9]{4}[ -][0-9]{1,4}|3[47][0-9]{2}[ -][0-9]{6}[ -][0-9]{5})(?![0-9])",
}
_ALL = "|".join(f"(?:{p})" for p in KINDS.values())


def _round(key: str, tweak: Column, i: Column, half: Column) -> Column:
    """60 bits of a keyed hash of a round's input."""
    return F.conv(F.substring(F.sha2(F.concat_ws("|", F.lit(key), tweak, i.cast("string"), half.cast("string")), 256), 1, 15), 16, 10).cast("long")


def permuted(key: str, tweak: Column, value: Column, low: Column, high: Column) -> Column:
    """A Feistel permutation of the pairs (value div high, value mod high), 0 <= value < low * high, as a struct l, r."""
    start = F.struct(F.floor(value / high).cast("long").alias("l"), F.pmod(value, high).cast("long").alias("r"))
    return _walk(key, tweak, start, low, high)


def _walk(key: str, tweak: Column, start: Column, low: Column, high: Column) -> Column:
    return F.aggregate(
        F.sequence(F.lit(0), F.lit(ROUNDS - 1)),
        start,
        lambda acc, i: F.when(i % 2 == 0, F.struct(F.pmod(acc["l"] + _round(key, tweak, i, acc["r"]), low).alias("l"), acc["r"].alias("r"))).otherwise(
            F.struct(acc["l"].alias("l"), F.pmod(acc["r"] + _round(key, tweak, i, acc["l"]), high).alias("r"))
        ),
    )


def _power(n: Column) -> Column:
    return F.rpad(F.lit("1"), n + 1, "0").cast("long")


def digits_permuted(key: str, tweak: Column, digits: Column) -> Column:
    """Another string of as many digits (36 at most), by a permutation of all strings of that length."""
    n = F.char_length(digits)
    a = F.floor(n / 2).cast("int")
    start = F.struct(F.coalesce(F.substring(digits, F.lit(1), a).cast("long"), F.lit(0).cast("long")).alias("l"), F.substring(digits, a + 1, n - a).cast("long").alias("r"))
    after = F.transform(F.array(_walk(key, F.concat_ws("/", tweak, n.cast("string")), start, _power(a), _power(n - a))), lambda s: F.concat(F.when(a > 0, F.lpad(s["l"].cast("string"), a, "0")).otherwise(F.lit("")), F.lpad(s["r"].cast("string"), n - a, "0")))
    return F.element_at(after, 1)


def luhn_sum(digits: Column) -> Column:
    """Sum by the Luhn rule; the last digit counts once."""
    n = F.char_length(digits)
    each = F.transform(F.split(digits, ""), lambda d, i: F.when(F.pmod(n - i, F.lit(2)) == 0, d.cast("int") * 2 - F.when(d.cast("int") > 4, 9).otherwise(0)).otherwise(d.cast("int")))
    return F.aggregate(F.filter(each, lambda d: d.isNotNull()), F.lit(0), lambda acc, d: acc + d)


def _refilled(mask: Column, digits: Column) -> Column:
    """mask with its digits replaced in order by digits."""
    marks = F.split(mask, "")
    walked = F.aggregate(
        marks,
        F.struct(F.lit(1).alias("at"), F.lit("").alias("out")),
        lambda acc, c: F.when(c.rlike("^[0-9]$"), F.struct((acc["at"] + 1).alias("at"), F.concat(acc["out"], F.substring(digits, acc["at"], F.lit(1))).alias("out"))).otherwise(F.struct(acc["at"].alias("at"), F.concat(acc["out"], c).alias("out"))),
        lambda acc: acc["out"],
    )
    return walked


def _with(value: Column, then) -> Column:
    """then(value) with value computed once."""
    return F.element_at(F.transform(F.array(value), then), 1)


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _card(key: str, x: Column) -> Column:
    def valid(d: Column) -> Column:
        issuer, n = F.substring(d, F.lit(1), F.lit(6)), F.char_length(d)
        body = digits_permuted(key, F.concat(F.lit("card/"), issuer), F.substring(d, F.lit(7), n - 7))
        made = _with(F.concat(issuer, body), lambda b: F.concat(b, F.pmod(10 - F.pmod(luhn_sum(F.concat(b, F.lit("0"))), F.lit(10)), F.lit(10)).cast("string")))
        return F.when((luhn_sum(d) % 10 == 0) & ~d.rlike("^0+$"), _refilled(x, made)).otherwise(x)

    return _with(_digits(x), valid)


#: Country codes of telephony: those of one and of two digits; all others have three. Fixed values.
COUNTRY = r"^(1|7|20|27|30|31|32|33|34|36|39|40|41|43|44|45|46|47|48|49|51|52|53|54|55|56|57|58|60|61|62|63|64|65|66|81|82|84|86|90|91|92|93|94|95|98|[2-9][0-9][0-9])"


def _phone(key: str, x: Column) -> Column:
    def made(d: Column) -> Column:
        country = F.regexp_extract(d, COUNTRY, 1)
        rest = F.substring(d, F.char_length(country) + 1, F.char_length(d))
        whole = _with(digits_permuted(key, F.concat(F.lit("phone/"), country), rest), lambda n: F.when(x.startswith("+"), F.concat(country, n)).otherwise(n))
        return F.when((country != "") & F.char_length(rest).between(7, 14) & (F.char_length(d) <= 15), _refilled(x, whole)).otherwise(x)

    return _with(F.when(x.startswith("+"), _digits(x)).otherwise(F.concat(F.lit("1"), _digits(x))), made)


def _social(key: str, x: Column) -> Column:
    real = ~x.rlike("^(000|666|9)|-00-|-0000$")

    def made(d: Column) -> Column:
        area, group, serial = (F.substring(d, F.lit(a), F.lit(n)).cast("long") for a, n in ((1, 3), (4, 2), (6, 4)))
        place = ((area - F.when(area > 666, 2).otherwise(1)) * 99 + group - 1) * 9999 + serial - 1
        lr = permuted(key, F.lit("social"), place, F.lit(898 * 99).cast("long"), F.lit(9999).cast("long"))
        return _with(lr, lambda s: F.concat_ws("-", *(F.lpad(v.cast("string"), n, "0") for v, n in ((F.floor(s["l"] / 99) + F.when(F.floor(s["l"] / 99) + 1 >= 666, 2).otherwise(1), 3), (s["l"] % 99 + 1, 2), (s["r"] + 1, 4)))))

    return F.when(real, _with(_digits(x), made)).otherwise(x)


def _address(key: str, x: Column) -> Column:
    parts = F.transform(F.split(x, r"\."), lambda p: p.cast("long"))

    def made(p: Column) -> Column:
        number = F.aggregate(p, F.lit(0).cast("long"), lambda acc, o: acc * 256 + o)
        lr = permuted(key, F.lit("address"), number, F.lit(65536).cast("long"), F.lit(65536).cast("long"))
        return _with(lr, lambda s: F.concat_ws(".", *(F.floor(v / 256).cast("string") if k == 0 else (v % 256).cast("string") for v in (s["l"], s["r"]) for k in (0, 1))))

    return _with(parts, lambda p: F.when(F.forall(p, lambda o: o <= 255), made(p)).otherwise(x))


#: Dates are permuted among all days of the years 1 to 9999: those up to the 12th of their month among themselves, and
#: those after it among themselves. So a date that reads month first only, day first never, stays one, and its pseudonym
#: is no other date's. The sides' products are 9999 * 12 * 12 and 9999 * 12 * 19 places. Fixed values.
_EARLY, _LATE, _MONTHS = (1188, 1212), (1254, 1818), 9999 * 12
#: Places after the 12th that are no days, such as 30 February: a walk meets so many at most. Fixed value.
_NO_DAYS = _LATE[0] * _LATE[1] - (3_652_059 - _EARLY[0] * _EARLY[1])


def _is_day(year: Column, month: Column, day: Column) -> Column:
    leap = ((year % 4 == 0) & (year % 100 != 0)) | (year % 400 == 0)
    last = F.when(month == 2, F.when(leap, 29).otherwise(28)).when(month.isin(4, 6, 9, 11), 30).otherwise(31)
    return (year >= 1) & month.between(1, 12) & day.between(1, last)


def _date(key: str, x: Column) -> Column:
    iso = x.rlike("^[0-9]{4}-")

    def walk(kind: str, sides: tuple[int, int], place: Column) -> Column:
        low, high = (F.lit(n).cast("long") for n in sides)
        return _with(permuted(key, F.lit(kind), place, low, high), lambda s: s["l"] * high + s["r"])

    def late(place: Column) -> Column:
        """Walks on until the place is a day again: a few steps nearly always, all that there can be if need be."""
        inside = lambda v: _is_day(F.floor(F.floor(v / 19) / 12) + 1, F.floor(v / 19) % 12 + 1, v % 19 + 13)
        step = lambda v: walk("date/late", _LATE, v)
        on = lambda v, most: F.when(inside(v), v).otherwise(F.aggregate(F.sequence(F.lit(1), F.lit(most)), v, lambda acc, _: F.when(inside(acc), acc).otherwise(step(acc))))
        return _with(_with(step(place), lambda v: on(v, 6)), lambda v: on(v, _NO_DAYS))

    def made(f: Column) -> Column:
        year, month, day = f["year"], f["month"], f["day"]
        of_month = (year - 1) * 12 + month - 1
        early = _with(walk("date/early", _EARLY, of_month * 12 + day - 1), lambda v: F.struct(F.floor(v / 12).alias("m"), (v % 12 + 1).alias("d")))
        later = _with(late(of_month * 19 + day - 13), lambda v: F.struct(F.floor(v / 19).alias("m"), (v % 19 + 13).alias("d")))

        def spelt(s: Column) -> Column:
            y, m, d = F.lpad((F.floor(s["m"] / 12) + 1).cast("string"), 4, "0"), F.lpad((s["m"] % 12 + 1).cast("string"), 2, "0"), F.lpad(s["d"].cast("string"), 2, "0")
            return _refilled(x, F.when(iso, F.concat(y, m, d)).when(f["month_first"], F.concat(m, d, y)).otherwise(F.concat(d, m, y)))

        return F.when(day <= 12, _with(early, spelt)).otherwise(_with(later, spelt))

    def read(p: Column) -> Column:
        """The date by ISO order, or day first, or, with slashes and if there is no such day, month first."""
        n = [p[k].cast("long") for k in range(3)]
        as_ = lambda y, m, d, first=False: F.struct(n[y].alias("year"), n[m].alias("month"), n[d].alias("day"), F.lit(first).alias("month_first"))
        orders = F.when(iso, as_(0, 1, 2)).when(_is_day(n[2], n[1], n[0]) | ~x.rlike("/.*/"), as_(2, 1, 0)).otherwise(as_(2, 0, 1, True))
        return _with(orders, lambda f: F.when(_is_day(f["year"], f["month"], f["day"]), made(f)).otherwise(x))

    return _with(F.split(x, "[-./]"), read)


def _iban(key: str, x: Column) -> Column:
    def remainder(s: Column) -> Column:
        spelt = F.concat_ws("", F.transform(F.split(s, ""), lambda c: F.when(c.rlike("[A-Z]"), (F.ascii(c) - 55).cast("string")).otherwise(c)))
        return F.aggregate(F.filter(F.split(spelt, ""), lambda c: c != ""), F.lit(0), lambda acc, c: F.pmod(acc * 10 + c.cast("int"), F.lit(97)))

    def made(s: Column) -> Column:
        account = F.substring(s, F.lit(5), F.char_length(s) - 4)
        digits = _digits(account)
        tail = _with(digits, lambda d: F.when(F.char_length(d) > 1, _refilled(account, digits_permuted(key, F.lit("iban"), d))).otherwise(account))
        return _with(tail, lambda t: F.concat(F.substring(s, F.lit(1), F.lit(2)), F.lpad((98 - remainder(F.concat(t, F.substring(s, F.lit(1), F.lit(2)), F.lit("00")))).cast("string"), 2, "0"), t))

    plain = F.regexp_replace(x, " ", "")
    return _with(plain, lambda s: F.when(remainder(F.concat(F.substring(s, F.lit(5), F.char_length(s)), F.substring(s, F.lit(1), F.lit(4)))) == 1, made(s)).otherwise(x))


def _email(key: str, x: Column) -> Column:
    """Of a host of the sender's own nothing stays but its last label; case doesn't tell two addresses apart."""
    return F.concat(F.lit("u"), F.substring(F.sha2(F.concat_ws("|", F.lit(key), F.lit("email"), F.lower(x)), 256), 1, 24), F.lit("@mail.invalid"))


_MADE = {"email": _email, "iban": _iban, "date": _date, "address": _address, "phone": _phone, "social": _social, "card": _card}


def pseudonym(key: str, x: Column) -> Column:
    """What stands for a candidate x; x itself if its kind's validation fails."""
    out = None
    for kind, pattern in KINDS.items():
        test = x.rlike(f"^(?:{pattern})$")
        out = F.when(test, _MADE[kind](key, x)) if out is None else out.when(test, _MADE[kind](key, x))
    return out.otherwise(x)


def pseudonymised(docs: DataFrame, key: str, *, text_column: str = "text") -> DataFrame:
    """docs with pseudonyms in text_column. One pass, no shuffle; texts without candidates aren't taken apart."""
    made, (_, _, after) = _replaced(docs, key, text_column)
    return made.select(*(F.col(after).alias(c) if c == text_column else F.col(f"`{c}`") for c in docs.columns))


def report(docs: DataFrame, key: str, *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id, text with pseudonyms, n_candidates, n_replaced."""
    rows = docs.select(F.col(f"`{id_column}`").alias("doc_id"), F.col(f"`{text_column}`").alias("text"))
    made, (found, pseudonyms, after) = _replaced(rows, key, "text")
    changed = F.aggregate(F.zip_with(found, pseudonyms, lambda a, b: (a != b).cast("long")), F.lit(0).cast("long"), lambda acc, x: acc + x)
    return made.select("doc_id", F.col(after).alias("text"), F.coalesce(F.size(found), F.lit(0)).cast("long").alias("n_candidates"), F.coalesce(changed, F.lit(0)).alias("n_replaced"))


def _replaced(docs: DataFrame, key: str, text_column: str) -> tuple[DataFrame, tuple[str, str, str]]:
    """docs with three more columns, and their names, which no column of docs has: candidates, pseudonyms, text after."""
    taken, names = {c.lower() for c in docs.columns}, []
    for name in ("found", "made", "after"):
        while name in taken:
            name = f"_{name}"
        names.append(name)
    found, made, after = names
    text = F.col(f"`{text_column}`")
    candidates = F.when(text.rlike("@|[0-9][^\\n]{0,40}[0-9]"), F.regexp_extract_all(text, F.lit(_ALL), F.lit(0))).otherwise(F.array().cast("array<string>"))
    taken_apart = docs.withColumn(found, candidates)
    pseudonyms = taken_apart.withColumn(made, F.transform(found, lambda x: pseudonym(key, x)))
    joined = F.array_join(F.flatten(F.zip_with(F.split(text, _ALL, -1), made, lambda gap, x: F.array(gap, F.coalesce(x, F.lit(""))))), "")
    return pseudonyms.withColumn(after, F.when(F.size(found) > 0, joined).otherwise(text)), (found, made, after)
