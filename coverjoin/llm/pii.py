"""Personal data: format-preserving pseudonyms by a keyed Feistel network, in Spark's own expressions only.

Found values that pass validation (card numbers by their check digit, phone numbers, social security numbers and IPv4
addresses by their ranges, dates by the calendar) and e-mail addresses are permuted within their own format: a card number
becomes another valid card number with the same grouping, a date another date in the same notation. The permutation depends
on the key alone, so equal values get equal pseudonyms in all documents, and whoever has the key can turn them back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import native
from .common import named, plain

ROUNDS = 10
EMAIL = r"[A-Za-z0-9](?:[A-Za-z0-9._%+-]*[A-Za-z0-9])?@[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?(?:\.[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?)*\.[A-Za-z]{2,}"
IP = r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\.?\d)"
DATE = r"(?<![\d/.-])(?:\d{4}([-/.])\d{2}\1\d{2}|\d{2}([/.-])\d{2}\2\d{4})(?!\d|[-/.]\d)"
SSN = r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"
PHONE = r"(?<![\d.+-])(?:\+?1[ .-]?)?(?:\([2-9]\d{2}\)[ .-]?|[2-9]\d{2}[ .-])[2-9]\d{2}[ .-]\d{4}(?!\d|[-.]\d)"
#: The usual groupings come first, so that a number behind or before the card (expiry, code, item) is not read into it; a number of
#: 19 digits grouped by four is therefore read as 16 digits and a code.
GROUPED = "|".join(sep.join(rf"\d{{{n}}}" for n in sizes) for sizes in ((4, 4, 4, 4), (4, 6, 5), (4, 6, 4)) for sep in (" ", "-"))
CARD = rf"(?<![\d.+-])(?:(?:{GROUPED})|(?!\d{{1,3}}[ -](?:{GROUPED})(?!\d))\d(?:[ -]?\d){{12,18}})(?!\d|[-.]\d)"
#: In the order in which they are tried at each position.
KINDS = {"email": EMAIL, "ip": IP, "date": DATE, "ssn": SSN, "phone": PHONE, "card": CARD}


#: Only DATE has groups, so its back references hold in the joined pattern.
ANY = "|".join(f"(?:{p})" for p in KINDS.values())


def _number(*parts: Column) -> Column:
    """A keyed 60-bit number from the parts."""
    return F.conv(F.substring(F.sha2(F.concat_ws("|", *parts), 256), 1, 15), 16, 10).cast("long")


def feistel_chars(value: Column, mask: Column, key: str, tweak: str, back: bool = False) -> Column:
    """Permute the characters of ``value`` within the classes that ``mask`` names for each position: d 0-9, n 2-9,
    a a-z, A A-Z; others stay."""
    base, size = {"d": 48, "n": 50, "a": 97, "A": 65}, {"d": 10, "n": 8, "a": 26, "A": 26}
    sign = -1 if back else 1

    def shift(c: Column, m: Column, k: Column) -> Column:
        out = c
        for x in base:
            out = F.when(m == x, F.chr(F.pmod(F.ascii(c) - base[x] + sign * k, F.lit(size[x])) + base[x])).otherwise(out)
        return out

    def turn(moved: Column, masks: Column, other: Column, i: Column) -> Column:
        seed = F.array_join(other, "")
        # one digest gives the shifts of 15 positions
        return F.transform(moved, lambda c, j: shift(c, F.element_at(masks, j + 1), F.conv(F.substring(F.sha2(F.concat_ws("|", F.lit(key), F.lit(tweak), i.cast("string"), seed, F.floor(j / 15).cast("string")), 256), 1 + 4 * (j % 15).cast("int"), 4), 16, 10).cast("int")))

    def step(s: Column, i: Column) -> Column:
        if back:
            i = F.lit(ROUNDS - 1) - i
            return F.struct(turn(s["r"], s["rm"], s["l"], i).alias("l"), s["rm"].alias("lm"), s["l"].alias("r"), s["lm"].alias("rm"))
        return F.struct(s["r"].alias("l"), s["rm"].alias("lm"), turn(s["l"], s["lm"], s["r"], i).alias("r"), s["lm"].alias("rm"))

    def run(v: Column, m: Column) -> Column:
        h = F.floor(F.length(v) / 2).cast("int")
        n = F.length(v)
        first = F.struct(native.chars(F.substring(v, F.lit(1), h)).alias("l"), native.chars(F.substring(m, F.lit(1), h)).alias("lm"), native.chars(F.substring(v, h + 1, n)).alias("r"), native.chars(F.substring(m, h + 1, n)).alias("rm"))
        return native.fold(first, ROUNDS, step)

    done = run(value, mask)
    return _let(done, lambda s: F.concat(F.array_join(s["l"], ""), F.array_join(s["r"], "")))


def _let(value: Column, use) -> Column:
    """Evaluate ``value`` once and use it by name."""
    return F.element_at(F.transform(F.array(value), use), 1)


def feistel_pair(x: Column, y: Column, a: int, b: int, key: str, tweak: str, back: bool = False) -> Column:
    """Permute the pairs (x, y) of 0..a-1 and 0..b-1: the two take turns in being shifted by a keyed number of the other."""
    def step(s: Column, i: Column) -> Column:
        i = F.lit(ROUNDS - 1) - i if back else i
        k = lambda other: _number(F.lit(key), F.lit(tweak), i.cast("string"), other.cast("string"))
        sign = -1 if back else 1
        even = i % 2 == 0
        return F.struct(F.when(even, F.pmod(s["x"] + sign * (k(s["y"]) % a), F.lit(a))).otherwise(s["x"]).cast("long").alias("x"), F.when(even, s["y"]).otherwise(F.pmod(s["y"] + sign * (k(s["x"]) % b), F.lit(b))).cast("long").alias("y"))

    return native.fold(F.struct(x.cast("long").alias("x"), y.cast("long").alias("y")), ROUNDS, step)


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, r"\D", "")


def _into(m: Column, digits: Column) -> Column:
    """Put new digits into the places of the old ones."""
    own = native.chars(m)
    return F.aggregate(own, F.struct(F.lit("").alias("s"), F.lit(0).alias("k")), lambda acc, c: F.when(c.between("0", "9"), F.struct(F.concat(acc["s"], F.substring(digits, acc["k"] + 1, F.lit(1))).alias("s"), (acc["k"] + 1).alias("k"))).otherwise(F.struct(F.concat(acc["s"], c).alias("s"), acc["k"].alias("k"))))["s"]


def luhn_sum(digits: Column, last_doubled: bool) -> Column:
    """Luhn sum of the digits from the right; ``last_doubled`` as for a number without its check digit."""
    odd = 0 if last_doubled else 1
    d = F.reverse(native.chars(digits))
    each = F.transform(d, lambda c, i: F.when(i % 2 == odd, F.when(c.cast("int") > 4, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)).otherwise(c.cast("int")))
    return F.aggregate(each, F.lit(0), lambda a, x: a + x)


def _card(m: Column, key: str, back: bool) -> Column:
    def use(d: Column) -> Column:
        body = F.substring(d, F.lit(1), F.length(d) - 1)
        new = feistel_chars(body, F.repeat(F.lit("d"), F.length(body)), key, "card", back)
        full = _let(new, lambda x: F.concat(x, F.pmod(-luhn_sum(x, True), F.lit(10)).cast("string")))
        return F.when(F.pmod(luhn_sum(d, False), F.lit(10)) == 0, _let(full, lambda x: _into(m, x)))

    return _let(_digits(m), use)


def _phone(m: Column, key: str, back: bool) -> Column:
    def use(d: Column) -> Column:
        own = F.right(d, F.lit(10))
        return _let(F.concat(F.substring(d, F.lit(1), F.length(d) - 10), feistel_chars(own, F.lit("nddndddddd"), key, "phone", back)), lambda x: _into(m, x))

    return _let(_digits(m), use)


def _ssn(m: Column, key: str, back: bool) -> Column:
    area, group, serial = (F.substring(m, a, n).cast("int") for a, n in ((1, 3), (5, 2), (8, 4)))
    k = F.when(area > 666, area - 2).otherwise(area - 1)  # 1..899 without 666
    new = feistel_pair(k * 99 + group - 1, serial - 1, 898 * 99, 9999, key, "ssn", back)
    out = _let(new, lambda p: _let(F.floor(p["x"] / 99).cast("int"), lambda q: F.concat_ws("-", F.lpad(F.when(q >= 665, q + 2).otherwise(q + 1).cast("string"), 3, "0"), F.lpad((p["x"] % 99 + 1).cast("string"), 2, "0"), F.lpad((p["y"] + 1).cast("string"), 4, "0"))))
    return F.when(area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0), out)


def _ip(m: Column, key: str, back: bool) -> Column:
    o = [F.split_part(m, F.lit("."), F.lit(i)).cast("long") for i in (1, 2, 3, 4)]
    plain = F.array_join(F.transform(F.split(m, r"\."), lambda x: x.cast("int").cast("string")), ".") == m
    new = feistel_pair(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, key, "ip", back)
    return F.when(plain & (F.greatest(*o) < 256), _let(new, lambda p: F.concat_ws(".", *(F.floor(p[c] / 256).cast("string") if hi else (p[c] % 256).cast("string") for c in ("x", "y") for hi in (True, False)))))


def _date(m: Column, key: str, back: bool) -> Column:
    """Calendar dates of 1900 to 2099 (17 * 4297 days): year first, or two-digit parts before the year, month first with a
    slash and day first with a dot or dash."""
    first = F.substring(m, 5, 1).rlike(r"\D")
    sep = F.when(first, F.substring(m, 5, 1)).otherwise(F.substring(m, 3, 1))
    two = [F.substring(m, 1, 2), F.substring(m, 4, 2)]
    y = F.when(first, F.substring(m, 1, 4)).otherwise(F.right(m, F.lit(4))).cast("int")
    mo = F.when(first, F.substring(m, 6, 2)).when(sep == "/", two[0]).otherwise(two[1]).cast("int")
    d = F.when(first, F.right(m, F.lit(2))).when(sep == "/", two[1]).otherwise(two[0]).cast("int")
    leap = (y % 4 == 0) & (y != 1900)
    days = F.when(mo.isin(4, 6, 9, 11), 30).when(mo == 2, F.when(leap, 29).otherwise(28)).otherwise(31)
    ok = y.between(1900, 2099) & mo.between(1, 12) & (d >= 1) & (d <= days)
    k = F.datediff(F.when(ok, F.make_date(y, mo, d)), F.lit("1900-01-01").cast("date"))
    new = feistel_pair(F.floor(k / 4297), k % 4297, 17, 4297, key, "date", back)
    write = lambda x: F.when(first, F.concat_ws("", F.date_format(x, "yyyy"), sep, F.date_format(x, "MM"), sep, F.date_format(x, "dd"))).when(sep == "/", F.concat_ws("", F.date_format(x, "MM"), sep, F.date_format(x, "dd"), sep, F.date_format(x, "yyyy"))).otherwise(F.concat_ws("", F.date_format(x, "dd"), sep, F.date_format(x, "MM"), sep, F.date_format(x, "yyyy")))
    return F.when(ok, _let(F.date_add(F.lit("1900-01-01").cast("date"), _let(new, lambda p: (p["x"] * 4297 + p["y"]).cast("int"))), write))


def _email(m: Column, key: str, back: bool) -> Column:
    """The local part's letters and digits move within their classes; the domain stays."""
    at = F.split_part(m, F.lit("@"), F.lit(1))
    mask = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(at, "[^A-Za-z0-9]", "-"), "[0-9]", "0"), "[a-z]", "a"), "[A-Z]", "A")
    return F.concat(feistel_chars(at, F.translate(mask, "0", "d"), key, "email", back), F.lit("@"), F.split_part(m, F.lit("@"), F.lit(2)))


def kind_of(m: Column) -> Column:
    out = F.lit(None).cast("string")
    for k, p in reversed(KINDS.items()):
        out = F.when(m.rlike(f"^(?:{p})$"), k).otherwise(out)
    return out


def pseudonym(m: Column, key: str, back: bool = False) -> Column:
    """(kind, value, pseudonym) of a match; the pseudonym is null where validation fails."""
    own = {"email": _email, "ip": _ip, "date": _date, "ssn": _ssn, "phone": _phone, "card": _card}

    def use(k: Column) -> Column:
        new = F.lit(None).cast("string")
        for name, f in own.items():
            new = F.when(k == name, f(m, key, back)).otherwise(new)
        return F.struct(k.alias("kind"), m.alias("value"), new.alias("pseudonym"))

    return _let(kind_of(m), use)


def pseudonymise(docs: DataFrame, key: str, text: str = "text", out: str = "text", findings: str = "findings", back: bool = False) -> DataFrame:
    """Rewrite ``text`` into ``out`` and add ``findings``, an array of (kind, value, pseudonym) in the order of the text.

    A null text gives null and no findings, an empty one itself. What fails validation stays. ``back=True`` with the same
    key restores the values. Columns named ``out`` or ``findings`` are replaced, others pass. Nothing is shuffled or cached;
    texts without a match are only scanned once.
    """
    docs, to = plain(docs)
    t = F.col(to[text])
    none = F.array().cast("array<struct<kind:string,value:string,pseudonym:string>>")
    found = F.when(t.rlike(ANY), F.transform(native.matches(t, ANY), lambda m: pseudonym(m, key, back))).otherwise(none)
    df = docs.withColumn("_found", F.coalesce(found, none))
    rewritten = F.when(F.size("_found") > 0, native.weave(native.gaps(t, ANY), F.transform("_found", lambda x: F.coalesce(x["pseudonym"], x["value"])))).otherwise(t)
    df = df.withColumn("_new", rewritten).withColumn("_valid", F.filter("_found", lambda x: x["pseudonym"].isNotNull()))
    return named(df, to, {out: "_new", findings: "_valid"})
