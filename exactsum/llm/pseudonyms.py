"""Format-preserving pseudonyms for personal numbers and dates, in DataFrame functions only.

Numbers and dates that pass their validation are permuted by a keyed Feistel network over exactly
their own domain, so a pseudonym keeps length, punctuation and validity, equal values get equal
pseudonyms in every document, and the key's holder can undo it.  Each kind is its own permutation.

  card   13-19 digits of one or more groups, single spaces or hyphens between them, Luhn-valid, also
         where other groups stand before or after: all digits but the last are permuted, and the
         last is computed anew
  phone  +country and 7-14 more digits, as many as its country has where that is one number, and
         never the start of an address, card, date or other number after a space; or 3-3-4 digits in
         the usual punctuation: the digits after the country code.  Ten digits of country 1 whose area
         and exchange can be dialled (200-999 without those that end in 11) move among such numbers,
         other ten digits among the others; a national number that starts with a digit above zero
         keeps doing so, and a leading zero stays
  ssn    3-2-4 digits with hyphens, with an area of 001-899 but 666, a group from 01 and a serial from
         0001: among these, and anything else stays
  ip     four octets up to 255: the 32-bit address
  date   yyyy-mm-dd (also before T and a time), dd.mm.yyyy or dd/mm/yyyy that exists in the
         calendar, or else mm.dd.yyyy or mm/dd/yyyy: days of 1900-2099 among themselves, all other
         days of the years 1-9999 among themselves; with the month first, days over 12 only
  email  letters among letters of their case, digits among digits, of the part before the @

Round functions are SHA-256 of key, kind, domain, round and half.  A half over base B is moved by
addition modulo B, which is a bijection for any B; a value that leaves the domain (dates, cards in runs) is
permuted again until it is back inside, so the whole is a bijection of the domain.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 8
#: Day numbers count from 0001-01-01.  Fixed values of the proleptic Gregorian calendar.
ALL_DAYS, MODERN_START, MODERN_DAYS = 3_652_059, 693_595, 73_049

#: What starts another number than the one before it, after a space.
IP = r"\d{1,3}(?:\.\d{1,3}){3}(?![\w]|\.\d)"
OTHER = IP + r"|\d{3}-\d{2}-\d{4}(?![\w-])|\d{4}-\d{2}-\d{2}(?!\d|-)|\d{2}([./])\d{2}\{same}\d{4}(?![\w]|[./]\d)|\d{3}[.-]\d{3}[.-]\d{4}(?![\w-])"
CARDS = r"\d{13,19}(?!\w)|\d{4}[ -]\d{4}[ -]\d{4}[ -]\d{1,7}(?!\w)|\d{4}[ -]\d{6}[ -]\d{4,5}(?!\w)"


def _other(name: str) -> str:
    """OTHER with its separator in a group of this name, so that patterns can be put together."""
    return OTHER.replace("([./])", f"(?<{name}>[./])").replace(r"\{same}", rf"\k<{name}>")


#: Digits after the country codes whose numbers have one length; fixed values of the national plans.
LENGTHS = {10: "1|7|44|52|57|90|91|92", 9: "27|31|33|34|41|48|61|351|380|420", 8: "45|47|65|852"}


def _phones() -> str:
    """International layouts: in one piece, of a country with one length, or up to six groups.

    A group after seven digits is not taken where another number starts.
    """
    known = [rf"(?<![\w+])\+(?:{codes})(?=[ .(-])(?:[ .-]?\(?\d\)?){{{n}}}(?![\w-])" for n, codes in LENGTHS.items()]
    digit = r"[ .()-]{0,2}\d"
    read = rf"\+\d{{1,3}}[ .(-]{digit * 7}{f'(?:{digit})?' * 7}", rf"\+\d{{4}}{digit * 4}{f'(?:{digit})?' * 7}"
    enough, settled = f"(?<={read[0]}|{read[1]})", f"(?<={read[0]} |{read[1]} )"
    more = rf"(?:[ .-]?(?!{settled}(?:{_other('p')}|{CARDS}))\d{{2,4}}){{1,5}}"
    groups = rf"(?<![\w+])\+\d{{1,3}}(?:[ .-]?\(\d{{1,4}}\))?[ .-]?\d{{1,4}}{more}(?![\w-]){enough}"
    return "|".join([r"(?<![\w+])\+\d{8,15}(?![\w-])", *known, groups])


def _cards() -> str:
    """Runs of digit groups with at least 13 digits, in which cards() looks for cards.

    A run ends before another kind of number, and before four groups of four digits after a group
    of another length.  A run of more than 200 groups is cut into several.
    """
    four = r"(?<!(?<!\d)\d{4} )\d{4}([ -]?)\d{4}\k<f>\d{4}\k<f>\d{4}(?!\w)".replace("([ -]?)", "(?<f>[ -]?)")
    return rf"(?<![\w-])(?=\d(?:[ -]?\d){{12}})\d++(?:(?:-| (?!{_other('c')}|{four}))\d++){{0,199}}(?!\w)"


PATTERNS = {
    "email": r"[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?(?:\.[A-Za-z0-9-]*[A-Za-z0-9])*\.[A-Za-z]{2,}",
    "phone": _phones() + r"|(?<![\w(])\(\d{3}\) ?\d{3}[.-]\d{4}(?![\w-])|(?<![\w.-])\d{3}[.-]\d{3}[.-]\d{4}(?![\w-])",
    "ssn": r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])",
    "ip": r"(?<![\w.])" + IP,
    "date": r"(?<![\w-])\d{4}-\d{2}-\d{2}(?:(?![\w-])|(?=[Tt]\d{2}))|(?<![\w./])\d{2}(?<s>[./])\d{2}\k<s>\d{4}(?![\w]|[./]\d)",
    "card": _cards(),
}
#: Number patterns in the order in which they are tried at a place.
NUMBERS = ("phone", "ssn", "ip", "date", "card")


def _hash(key: str, kind: str, base: Column, other: Column, turn: Column, value: Column) -> Column:
    """A number below `base` from the other half."""
    text = F.concat_ws("|", F.lit(key), F.lit(kind), base.cast("string"), other.cast("string"), turn.cast("string"), value.cast("string"))
    return F.conv(F.substring(F.sha2(text, 256), 1, 15), 16, 10).cast("long") % base


def feistel(value: Column, left: Column, right: Column, key: str, kind: str, inverse: bool = False) -> Column:
    """A keyed permutation of 0 .. left*right-1; both bases are long columns up to 10^9."""
    turns = range(ROUNDS)[::-1] if inverse else range(ROUNDS)
    state = F.struct(_div(value, right).alias("a"), (value % right).alias("b"))
    sign = -1 if inverse else 1

    def step(s, turn):
        one = F.struct(F.pmod(s["a"] + sign * _hash(key, kind, left, right, turn, s["b"]), left).alias("a"), s["b"].alias("b"))
        two = F.struct(s["a"].alias("a"), F.pmod(s["b"] + sign * _hash(key, kind, right, left, turn, s["a"]), right).alias("b"))
        return F.when(turn % 2 == 0, one).otherwise(two)

    return F.aggregate(F.array(*[F.lit(t) for t in turns]), state, step, lambda s: s["a"] * right + s["b"])


def _div(value: Column, by: Column) -> Column:
    """Whole quotient; the division itself is of at most 18 digits by a power of ten or a small base."""
    return F.call_function("div", value, by)


def _power(n: Column) -> Column:
    """10^n as a long, for n up to 9."""
    return F.get(F.array(*[F.lit(10**k).cast("long") for k in range(10)]), n)


def permuted_digits(digits: Column, key: str, kind: str, inverse: bool = False) -> Column:
    """A string of 2 to 18 digits as another of the same length."""
    n = F.length(digits)
    right = _power((n / 2).cast("int"))
    left = _power(n - (n / 2).cast("int"))
    return F.lpad(feistel(digits.cast("long"), left, right, key, kind, inverse).cast("string"), n, "0")


def luhn_sum(digits: Column, doubled_from: int) -> Column:
    """Luhn's sum; `doubled_from` 1 doubles the last but one digit of a whole number, 0 the last of a number without its check digit."""
    places = F.transform(F.filter(F.split(F.reverse(digits), ""), lambda x: x != ""), lambda x: x.cast("int"))

    def value(x, i):
        twice = x * 2 - F.when(x > 4, 9).otherwise(0)
        return F.when(i % 2 == doubled_from, twice).otherwise(x)

    return F.aggregate(F.transform(places, value), F.lit(0), lambda a, x: a + x)


def filled(template: Column, digits: Column) -> Column:
    """The template with its digits replaced, one after the other."""
    chars = F.filter(F.split(template, ""), lambda x: x != "")
    start = F.struct(F.lit("").alias("out"), F.lit(1).alias("next"))

    def step(s, x):
        is_digit = x.rlike("[0-9]")
        return F.struct(F.concat(s["out"], F.when(is_digit, F.substr(digits, s["next"], F.lit(1))).otherwise(x)).alias("out"), (s["next"] + is_digit.cast("int")).alias("next"))

    return F.aggregate(chars, start, step, lambda s: s["out"])


def _let(value: Column, use) -> Column:
    """use(value) with `value` computed once."""
    return F.get(F.transform(F.array(value), use), 0)


def only_digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def card(digits: Column, key: str, inverse: bool = False) -> Column:
    body = permuted_digits(F.substr(digits, F.lit(1), F.length(digits) - 1), key, "card", inverse)
    return F.concat(body, F.pmod(10 - luhn_sum(body, 0), F.lit(10)).cast("string"))


def cards(text: Column, key: str, inverse: bool = False) -> Column:
    """A run of digit groups with its cards permuted.

    From each group on, the shortest 13-19 digits that end with a group and are Luhn-valid are a
    card; the search goes on after it.  A pseudonym that would let the search find other cards is
    permuted again, so the key's holder finds the same places: cards are changed from the last to
    the first and undone from the first to the last.
    """
    one = F.lit(1)
    part = lambda d, w: F.substr(d, w["a"] + one, w["b"] - w["a"])
    valid = lambda d, w: luhn_sum(part(d, w), 1) % 10 == 0

    def windows(groups):
        """Of 13 to 19 digits, by start and then by length."""
        ends = F.aggregate(groups, F.array(F.lit(0)), lambda e, g: F.concat(e, F.array(F.element_at(e, -1) + F.length(g))))
        at = lambda e, a, i: F.transform(F.filter(F.slice(e, i + 2, 19), lambda b: (b - a).between(13, 19)), lambda b: F.struct(a.alias("a"), b.alias("b")))
        return _let(ends, lambda e: F.flatten(F.transform(e, lambda a, i: at(e, a, i))))

    def search(d, found):
        none = F.array().cast("array<struct<a:int,b:int>>")
        start = F.struct(F.lit(0).alias("next"), none.alias("cards"), none.alias("others"))

        def step(s, w):
            hit = F.struct(w["b"].alias("next"), F.concat(s["cards"], F.array(w)).alias("cards"), s["others"].alias("others"))
            miss = F.struct(s["next"].alias("next"), s["cards"].alias("cards"), F.concat(s["others"], F.array(w)).alias("others"))
            return F.when(w["a"] < s["next"], s).when(valid(d, w), hit).otherwise(miss)

        return F.aggregate(found, start, step)

    def moved(d, w):
        return F.concat(F.substr(d, one, w["a"]), card(part(d, w), key, inverse), F.substr(d, w["b"] + one, F.length(d)))

    def changed(d, s):
        def walk(x, w):
            near = F.filter(s["others"], lambda o: (o["a"] < w["b"]) & (o["b"] > w["a"]))
            # other windows are valid in one of ten pseudonyms each
            return F.aggregate(F.sequence(F.lit(1), F.lit(100)), moved(x, w), lambda y, _: F.when(F.exists(near, lambda o: valid(y, o)), moved(y, w)).otherwise(y))

        return F.aggregate(s["cards"] if inverse else F.reverse(s["cards"]), d, walk)

    digits = only_digits(text)
    return _let(search(digits, windows(F.split(text, "[ -]"))), lambda s: F.when(F.size(s["cards"]) > 0, filled(text, changed(digits, s))).otherwise(text))


#: Three-digit codes that can be dialled: 2-9, then two digits that aren't 11.  Fixed values of the numbering plan.
CODES = 8 * 99


def _dialled(code: Column) -> Column:
    return code.rlike("^[2-9](?!11)[0-9]{2}$")


def _code_rank(code: Column) -> Column:
    low = code.cast("long") % 100
    return (F.substring(code, 1, 1).cast("long") - 2) * 99 + low - (low > 11).cast("long")


def _code(rank: Column) -> Column:
    low = rank % 99
    return F.concat((_div(rank, F.lit(99).cast("long")) + 2).cast("string"), F.lpad((low + (low >= 11).cast("long")).cast("string"), 2, "0"))


def _ten_digits(digits: Column, key: str, inverse: bool) -> Column:
    """Numbers that can be dialled among themselves, by rank; the others among themselves, by walking past the former."""
    valid = lambda d: _dialled(F.substring(d, 1, 3)) & _dialled(F.substring(d, 4, 3))
    tail = F.lit(10_000).cast("long")
    rank = (_code_rank(F.substring(digits, 1, 3)) * CODES + _code_rank(F.substring(digits, 4, 3))) * tail + F.substring(digits, 7, 4).cast("long")

    def number(x):
        head = _div(x, tail)
        codes = F.lit(CODES).cast("long")
        return F.concat(_code(_div(head, codes)), _code(head % codes), F.lpad((x % tail).cast("string"), 4, "0"))

    inside = _let(feistel(rank, F.lit(CODES * CODES).cast("long"), tail, key, "dialled", inverse), number)
    moved = lambda d: permuted_digits(d, key, "phone", inverse)
    # two of three numbers can be dialled; a hundred steps in a row are never
    outside = F.aggregate(F.sequence(F.lit(1), F.lit(100)), moved(digits), lambda d, _: F.when(valid(d), moved(d)).otherwise(d))
    return F.when(valid(digits), inside).otherwise(outside)


def _national(digits: Column, key: str, inverse: bool) -> Column:
    """7 to 15 digits; the first is zero before and after, or neither."""
    n = F.length(digits)
    half = (n / 2).cast("int")
    least = F.rpad(F.lit("1"), n, "0").cast("long")
    above = feistel(digits.cast("long") - least, 9 * _power(n - 1 - half), _power(half), key, "national", inverse) + least
    zero = F.concat(F.lit("0"), permuted_digits(F.substr(digits, F.lit(2), n - 1), key, "national", inverse))
    return F.when(digits.startswith("0"), zero).otherwise(above.cast("string"))


def phone(text: Column, key: str, inverse: bool = False) -> Column:
    code = F.regexp_extract(text, r"^\+\d{1,3}(?=[ .(-])|^\+1(?=\d{10}$)", 0)
    rest = F.substr(text, F.length(code) + 1, F.length(text))

    def changed(digits):
        ten = code.isin("", "+1") & ~rest.startswith("+") & (F.length(digits) == 10)
        return F.when(ten, _ten_digits(digits, key, inverse)).otherwise(_national(digits, key, inverse))

    return _let(only_digits(rest), lambda d: F.when(F.length(d).between(7, 15), F.concat(code, filled(rest, changed(d)))).otherwise(text))


def ssn(text: Column, key: str, inverse: bool = False) -> Column:
    area, group, serial = (F.substring(text, at, n).cast("long") for at, n in ((1, 3), (5, 2), (8, 4)))
    valid = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    serials, groups = F.lit(9999).cast("long"), F.lit(99).cast("long")
    rank = ((area - 1 - (area > 666).cast("long")) * groups + group - 1) * serials + serial - 1

    def written(x):
        head = _div(x, serials)
        place = _div(head, groups)
        parts = (place + 1 + (place >= 665).cast("long"), 3), (head % groups + 1, 2), (x % serials + 1, 4)
        return F.concat_ws("-", *[F.lpad(v.cast("string"), n, "0") for v, n in parts])

    moved = _let(feistel(rank, F.lit(898 * 99).cast("long"), serials, key, "ssn", inverse), written)
    return F.when(valid, moved).otherwise(text)


def ip(text: Column, key: str, inverse: bool = False) -> Column:
    octets = F.transform(F.split(text, r"\."), lambda x: x.cast("long"))
    number = F.aggregate(octets, F.lit(0).cast("long"), lambda a, x: a * 256 + x)
    half = F.lit(65536).cast("long")
    moved = feistel(number, half, half, key, "ip", inverse)
    out = F.concat_ws(".", *[F.pmod(F.shiftright(moved, 8 * k), F.lit(256)).cast("string") for k in (3, 2, 1, 0)])
    return F.when(F.forall(octets, lambda x: x <= 255), out).otherwise(text)


def date(text: Column, key: str, inverse: bool = False) -> Column:
    iso = text.rlike(r"^\d{4}-")
    plain = F.translate(text, "./", "--")
    day_first = F.try_to_timestamp(plain, F.lit("dd-MM-yyyy"))
    month_first = ~iso & day_first.isNull()
    parsed = F.when(iso, F.try_to_timestamp(text, F.lit("yyyy-MM-dd"))).otherwise(F.coalesce(day_first, F.try_to_timestamp(plain, F.lit("MM-dd-yyyy")))).cast("date")
    read = F.struct(F.datediff(parsed, F.lit("0001-01-01").cast("date")).cast("long").alias("day"), month_first.alias("month_first"))
    return _let(read, lambda r: F.when(r["day"].between(0, ALL_DAYS - 1), _moved_day(text, iso, r["day"], r["month_first"], key, inverse)).otherwise(text))


def _moved_day(text: Column, iso: Column, day: Column, month_first: Column, key: str, inverse: bool) -> Column:
    modern = day.between(MODERN_START, MODERN_START + MODERN_DAYS - 1)
    index = F.when(modern, day - MODERN_START).when(day < MODERN_START, day).otherwise(day - MODERN_DAYS)
    size = F.when(modern, MODERN_DAYS).otherwise(ALL_DAYS - MODERN_DAYS).cast("long")
    right = F.when(modern, 271).otherwise(1892).cast("long")
    left = F.when(modern, 270).otherwise(1892).cast("long")

    def as_date(x):
        back = F.when(modern, x + MODERN_START).when(x < MODERN_START, x).otherwise(x + MODERN_DAYS)
        return F.date_add(F.lit("0001-01-01").cast("date"), back.cast("int"))

    def again(x, _):
        inside = F.when(x >= size, False).when(month_first, F.dayofmonth(as_date(x)) > 12).otherwise(True)
        return F.when(inside, x).otherwise(feistel(x, left, right, key, "date", inverse))

    def written(new):
        sep, d, m, y = F.substring(text, 3, 1), F.date_format(new, "dd"), F.date_format(new, "MM"), F.date_format(new, "yyyy")
        return F.when(iso, F.date_format(new, "yyyy-MM-dd")).when(month_first, F.concat(m, sep, d, sep, y)).otherwise(F.concat(d, sep, m, sep, y))

    # a step leaves the domain with probability below 0.2 %, or about 40 % where the month comes first
    turns = F.sequence(F.lit(1), F.when(month_first, 60).otherwise(12))
    return _let(as_date(F.aggregate(turns, feistel(index, left, right, key, "date", inverse), again)), written)


def email(text: Column, key: str, inverse: bool = False) -> Column:
    """Each letter or digit of the local part moves within its own class, by an amount that depends on
    the classes of all its characters, on its place and on what stands before it."""
    local, rest = F.substring_index(text, "@", 1), F.regexp_extract(text, "@.*$", 0)
    chars = F.filter(F.split(local, ""), lambda x: x != "")
    shape = F.regexp_replace(F.regexp_replace(F.regexp_replace(local, "[0-9]", "0"), "[a-z]", "a"), "[A-Z]", "A")
    sign = -1 if inverse else 1

    def step(forward: bool):
        def go(s, x):
            base = F.when(x.rlike("[0-9]"), 10).when(x.rlike("[A-Za-z]"), 26).otherwise(1)
            first = F.when(x.rlike("[0-9]"), 48).when(x.rlike("[a-z]"), 97).when(x.rlike("[A-Z]"), 65).otherwise(F.ascii(x))
            shift = _hash(key, f"email {forward}", base.cast("long"), F.length(shape), F.concat(shape, rest), s["seen"])
            moved = F.char(first + F.pmod(F.ascii(x) - first + sign * shift, base))
            return F.struct(F.concat(s["out"], moved).alias("out"), F.concat(s["seen"], x if not inverse else moved).alias("seen"))

        return go

    def passed(letters: Column, forward: bool) -> Column:
        start = F.struct(F.lit("").alias("out"), F.lit("").alias("seen"))
        return F.aggregate(letters, start, step(forward), lambda s: s["out"])

    def reversed_chars(x: Column) -> Column:
        return F.filter(F.split(F.reverse(x), ""), lambda c: c != "")

    # one pass from the left and one from the right, so every character depends on all others
    if not inverse:
        return F.concat(F.reverse(passed(reversed_chars(passed(chars, True)), False)), rest)
    return F.concat(passed(F.filter(F.split(F.reverse(passed(reversed_chars(local), False)), ""), lambda c: c != ""), True), rest)


def pseudonym(found: Column, key: str, inverse: bool = False) -> Column:
    """Of one match of a number pattern; what fails its validation stays."""
    digits = F.length(only_digits(found))
    return (
        F.when(found.rlike(r"^\d{1,3}(\.\d{1,3}){3}$"), ip(found, key, inverse))
        .when(found.rlike(r"^\d{3}-\d{2}-\d{4}$"), ssn(found, key, inverse))
        .when(found.rlike(r"^(\d{4}-\d{2}-\d{2}|\d{2}[./]\d{2}[./]\d{4})$"), date(found, key, inverse))
        .when(found.rlike(r"^[+(]|^\d{3}[.-]\d{3}[.-]\d{4}$"), phone(found, key, inverse))
        .when(digits >= 13, cards(found, key, inverse))
        .otherwise(found)
    )


def _replaced(text: Column, pattern: str, change) -> Column:
    between = F.split(text, pattern, -1)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    pairs = F.zip_with(between, F.transform(found, change), lambda a, b: F.concat(a, F.coalesce(b, F.lit(""))))
    return F.array_join(pairs, "")


def pseudonymised(docs: DataFrame, key: str, text: str = "text", inverse: bool = False) -> DataFrame:
    """docs with personal numbers, dates and e-mail names in `text` replaced; other columns stay.

    Null and empty texts stay; every row is treated alone, so ties and repeated rows need no care.
    Only rows with a digit or an @ are taken apart.  `inverse` undoes it with the same key.
    """
    t = F.col(text)
    number = "|".join(PATTERNS[k] for k in NUMBERS)

    def numbers(x):
        return F.when(x.rlike(number), _replaced(x, number, lambda m: pseudonym(m, key, inverse))).otherwise(x)

    def emails(x):
        return F.when(x.contains("@"), _replaced(x, PATTERNS["email"], lambda m: email(m, key, inverse))).otherwise(x)

    changed = docs.withColumn(text, F.when(t.rlike("[0-9@]"), emails(t)).otherwise(t))
    return changed.withColumn(text, F.when(t.rlike("[0-9]"), numbers(t)).otherwise(t)).select(*docs.columns)
