"""Format-preserving Feistel pseudonyms (native) for validated numbers and dates in texts.

A value becomes a list of symbols, each with the number of values that its place allows (10 for a digit, 26 for a letter, 256
for an address part, and so on). Rounds of a keyed alternating Feistel network add a hash of one half to the other, place by place,
modulo these numbers: a permutation of all values of that format. Check digits are worked out anew, so a valid card
number stays a valid card number; a date stays a date. Equal values have equal pseudonyms in all documents.

Kinds and their checks: card (13 to 19 digits, check digit by doubling), IBAN (remainder 1 by 97; whole or printed in groups of four), social security number
(no zero group), phone (+1 and ten digits), IPv4 (parts to 255), date (exists, years 1800 to 2199; yyyy-mm-dd, dd.mm.yyyy or dd/mm/yyyy, each permuted in its own
format), e-mail (its local part). A run of digit groups that is no card as a whole is tried without up to two groups at either end. Candidates that fail their
check stay as they are; a month before its day, and more than 19 digits in groups, are not looked into.

The key is the caller's: whoever has it can undo the permutation. The registered query takes it from the session (`KEY_SETTING`) and, where none is set, uses a
key named as not secret.

Defined results: null text stays null with counts 0; a text without values is unchanged; repeated rows give repeated rows; an empty table gives
an empty result; all other columns are handed on as they are, whatever their names. The kinds found are in a column of the caller's naming, which must be new.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

ROUNDS = 8
KEY_SETTING, OPEN_KEY = "spark.tallygrid.pseudonymKey", "not-secret"
#: Hexadecimal digits of a mask, and masks in one 512-bit digest.
MASK, MASKS = 6, 21
#: The patterns of the kinds, most specific first.
KINDS = {
    "email": r"[A-Za-z0-9][A-Za-z0-9._%+\-]*@[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)*\.[A-Za-z]{2,}",
    "iban": r"\b[A-Z]{2}[0-9]{2}(?:[A-Z0-9]{11,30}|(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?)\b",
    "phone": r"\+1 ?\(?[0-9]{3}\)?[ .\-]?[0-9]{3}[ .\-]?[0-9]{4}\b",
    "date": r"\b(?:(?:18|19|20|21)[0-9]{2}-[0-9]{2}-[0-9]{2}|[0-3][0-9]([./])[01][0-9]\1(?:18|19|20|21)[0-9]{2})\b",
    "ssn": r"\b[0-9]{3}-[0-9]{2}-[0-9]{4}\b",
    "ip": r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9]|\.[0-9])",
    "card": r"(?<![0-9])[0-9](?:[ \-]?[0-9]){12,18}(?![0-9])",
}
PATTERN = "|".join(KINDS.values())
#: Days of 400 years, and two numbers whose product they are.
DAYS, DAY_HIGH, DAY_LOW = 146_097, 189, 773


def _chars(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def _feistel(symbols: Column, sizes: Column, key: str, kind: str) -> Column:
    half = F.floor((F.size(symbols) + 1) / 2).cast("int")
    steps = F.sequence(F.lit(0), F.lit(ROUNDS - 1))

    def turn(state: Column, step: Column) -> Column:
        left = step % 2 == 0
        other = F.when(left, F.slice(state, half + 1, F.size(state))).otherwise(F.slice(state, 1, half))
        digest = F.sha2(F.concat_ws("|", F.lit(key), F.lit(kind), F.size(state).cast("string"), step.cast("string"), F.concat_ws(",", other.cast("array<string>"))), 512)

        def place(x: Column, i: Column, own: Column) -> Column:
            source = F.when(i < MASKS, own).otherwise(F.sha2(F.concat_ws("|", own, F.floor(i / MASKS).cast("string")), 512))
            mask = F.conv(F.substr(source, (i % MASKS) * MASK + 1, F.lit(MASK)), 16, 10).cast("long")
            return F.when((i < half) == left, F.pmod(x + mask, F.element_at(sizes, (i + 1).cast("int")))).otherwise(x)

        # As the variable of an outer function the digest is worked out once a round, not once a place.
        return F.get(F.transform(F.array(digest), lambda own: F.transform(state, lambda x, i: place(x, i, own))), F.lit(0))

    return F.aggregate(steps, symbols, turn)


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def _refill(shape: Column, digits: Column) -> Column:
    """`shape` with its digits, in order, replaced by those of `digits`."""
    start = F.struct(F.lit("").alias("out"), F.lit(1).alias("at"))
    step = lambda s, c: F.when(c.rlike("[0-9]"), F.struct(F.concat(s["out"], F.substr(digits, s["at"], F.lit(1))).alias("out"), (s["at"] + 1).alias("at"))).otherwise(F.struct(F.concat(s["out"], c).alias("out"), s["at"].alias("at")))
    return F.aggregate(_chars(shape), start, step, lambda s: s["out"])


def _longs(text: Column) -> Column:
    return F.transform(_chars(text), lambda c: c.try_cast("long"))


def _tens(symbols: Column) -> Column:
    return F.transform(symbols, lambda _: F.lit(10).cast("long"))


def _luhn(digits: Column) -> Column:
    """Sum of a number's digits with every second one from the right doubled."""
    return F.aggregate(F.transform(F.reverse(_longs(digits)), lambda d, i: F.when(i % 2 == 1, F.when(d > 4, d * 2 - 9).otherwise(d * 2)).otherwise(d)), F.lit(0).cast("long"), lambda a, d: a + d)


def _card(value: Column, key: str) -> Column:
    ends = [(a, b) for a, b in sorted(((a, b) for a in range(3) for b in range(3)), key=sum)]
    parts = [F.regexp_extract(value, rf"^((?:[0-9]+[ \-]){{{a}}})([0-9][0-9 \-]*?)((?:[ \-][0-9]+){{{b}}})$", n) for a, b in ends for n in (1, 2, 3)]
    spans = F.array(*[F.struct(parts[k].alias("head"), parts[k + 1].alias("span"), parts[k + 2].alias("tail")) for k in range(0, len(parts), 3)])
    valid = F.filter(spans, lambda s: F.length(_digits(s["span"])).between(13, 19) & (F.pmod(_luhn(_digits(s["span"])), F.lit(10)) == 0))
    return F.get(F.transform(F.slice(valid, 1, 1), lambda s: F.concat(s["head"], _new_card(s["span"], key), s["tail"])), F.lit(0))


def _new_card(value: Column, key: str) -> Column:
    digits = _digits(value)
    body = F.substr(digits, F.lit(1), F.length(digits) - 1)
    new = F.concat_ws("", _feistel(_longs(body), _tens(_longs(body)), key, "card").cast("array<string>"))
    check = F.pmod(F.lit(10) - F.pmod(_luhn(F.concat(new, F.lit("0"))), F.lit(10)), F.lit(10))
    return _refill(value, F.concat(new, check.cast("string")))


def _mod97(text: Column) -> Column:
    """Remainder by 97 of a text whose letters stand for 10 to 35."""
    code = lambda c: F.when(c.rlike("[0-9]"), c.try_cast("long")).otherwise(F.ascii(c).cast("long") - 55)
    return F.aggregate(_chars(text), F.lit(0).cast("long"), lambda a, c: F.pmod(F.when(c.rlike("[0-9]"), a * 10).otherwise(a * 100) + code(c), F.lit(97)))


def _iban(value: Column, key: str) -> Column:
    plain = F.regexp_replace(value, " ", "")
    country, body = F.substr(plain, F.lit(1), F.lit(2)), F.substr(plain, F.lit(5), F.length(plain) - 4)
    new = _alike(body, key, "iban")
    check = F.lit(98) - _mod97(F.concat(new, country, F.lit("00")))
    valid = _mod97(F.concat(body, F.substr(plain, F.lit(1), F.lit(4)))) == 1
    whole = F.concat(country, F.lpad(check.cast("string"), 2, "0"), new)
    grouped = F.trim(F.regexp_replace(whole, "(.{4})", "$1 "))
    return F.when(valid, F.when(value.contains(" "), grouped).otherwise(whole))


def _alike(value: Column, key: str, kind: str) -> Column:
    """Digits to digits, letters to letters of the same case; all other characters stay."""
    chars = _chars(value)
    low = lambda c: F.when(c.rlike("[0-9]"), F.lit(48)).when(c.rlike("[a-z]"), F.lit(97)).when(c.rlike("[A-Z]"), F.lit(65)).otherwise(F.ascii(c))
    sizes = F.transform(chars, lambda c: F.when(c.rlike("[0-9]"), F.lit(10)).when(c.rlike("[A-Za-z]"), F.lit(26)).otherwise(F.lit(1)).cast("long"))
    symbols = F.transform(chars, lambda c: (F.ascii(c) - low(c)).cast("long"))
    return F.concat_ws("", F.zip_with(_feistel(symbols, sizes, key, kind), chars, lambda x, c: F.char(x + low(c))))


def _phone(value: Column, key: str) -> Column:
    digits = _longs(F.substr(_digits(value), F.lit(2), F.lit(10)))
    heads = lambda i: (i == 0) | (i == 3)  # noqa: E731  the first digits of area and exchange stay in 0-1 or in 2-9
    sizes = F.transform(digits, lambda d, i: F.when(heads(i), F.when(d < 2, F.lit(2)).otherwise(F.lit(8))).otherwise(F.lit(10)).cast("long"))
    base = lambda d, i: F.when(heads(i) & (d >= 2), F.lit(2)).otherwise(F.lit(0)).cast("long")
    moved = _feistel(F.transform(digits, lambda d, i: d - base(d, i)), sizes, key, "phone")
    lows = F.transform(digits, base)
    return _refill(value, F.concat(F.lit("1"), F.concat_ws("", F.zip_with(moved, lows, lambda x, b: x + b).cast("array<string>"))))


def _ssn(value: Column, key: str) -> Column:
    parts = F.transform(F.split(value, "-"), lambda p: p.try_cast("long"))
    sizes = F.array(*[F.lit(n).cast("long") for n in (999, 99, 9999)])
    moved = _feistel(F.transform(parts, lambda p: p - 1), sizes, key, "ssn")
    text = F.concat_ws("-", *[F.lpad((F.element_at(moved, i) + 1).cast("string"), n, "0") for i, n in ((1, 3), (2, 2), (3, 4))])
    return F.when(F.forall(parts, lambda p: p > 0), text)


def _ip(value: Column, key: str) -> Column:
    parts = F.transform(F.split(value, r"\."), lambda p: p.try_cast("long"))
    moved = _feistel(parts, F.transform(parts, lambda _: F.lit(256).cast("long")), key, "ip")
    return F.when(F.forall(parts, lambda p: p <= 255), F.concat_ws(".", moved.cast("array<string>")))


def _date(value: Column, key: str) -> Column:
    found = None
    first = F.lit("1800-01-01").cast("date")
    for shape in ("yyyy-MM-dd", "dd.MM.yyyy", "dd/MM/yyyy"):
        day = F.try_to_timestamp(value, F.lit(shape)).cast("date")
        number = F.datediff(day, first).cast("long")
        moved = _feistel(F.array(F.floor(number / DAY_LOW), F.pmod(number, F.lit(DAY_LOW))), F.array(F.lit(DAY_HIGH).cast("long"), F.lit(DAY_LOW).cast("long")), key, "date")
        new = F.when(day.isNotNull(), F.date_format(F.date_add(first, (F.element_at(moved, 1) * DAY_LOW + F.element_at(moved, 2)).cast("int")), shape))
        is_it = value.contains(shape[2] if shape[2] != "y" else "-")
        found = F.when(is_it, new) if found is None else found.when(is_it, new)
    return found


def _email(value: Column, key: str) -> Column:
    return F.concat(_alike(F.substring_index(value, "@", 1), key, "email"), F.lit("@"), F.substring_index(value, "@", -1))


MAKERS = {"email": _email, "iban": _iban, "phone": _phone, "date": _date, "ssn": _ssn, "ip": _ip, "card": _card}


def pseudonym(value: Column, key: str) -> Column:
    """struct(kind, new): null kind if no check holds."""
    found = None
    for kind, pattern in KINDS.items():
        test, new = value.rlike(f"^(?:{pattern})$"), MAKERS[kind](value, key)
        pair = F.struct(F.when(new.isNotNull(), F.lit(kind)).alias("kind"), F.coalesce(new, value).alias("new"))
        found = F.when(test, pair) if found is None else found.when(test, pair)
    return found.otherwise(F.struct(F.lit(None).cast("string").alias("kind"), value.alias("new")))


def pseudonymise(df: DataFrame, key: str, column: str = "text", kinds: str = "pii_kinds") -> DataFrame:
    """`df` with `column` rewritten, and `kinds`: the kinds of its replaced values, in order.

    Texts without a candidate, nearly all, skip the symbol work: values and gaps are found by one pattern, and the gaps are joined with the new
    values again.
    """
    if not key:
        raise ValueError("pseudonyms need a key")
    if kinds in df.columns:
        raise ValueError(f"the table has a column {kinds} already: name another for the kinds")
    text = F.col(f"__row.`{column}`")
    rows = df.select(F.struct("*").alias("__row"))
    found = rows.withColumn("__values", F.when(text.rlike("[0-9@]"), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))))
    found = found.withColumn("__new", F.when(F.size("__values") > 0, F.transform("__values", lambda v: pseudonym(v, key))))
    gaps = F.split(text, PATTERN, -1)
    joined = F.concat_ws("", F.zip_with(gaps, F.col("__new.new"), lambda g, n: F.concat(g, F.coalesce(n, F.lit("")))))
    new = F.when(F.col("__new").isNotNull(), joined).otherwise(text)
    found_kinds = F.coalesce(F.filter(F.col("__new.kind"), lambda k: k.isNotNull()), F.array().cast("array<string>"))
    return found.select(*[new.alias(c) if c == column else F.col(f"__row.`{c}`").alias(c) for c in df.columns], found_kinds.alias(kinds))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = pseudonymise(table(spark, sf_dir, "documents", "doc_id", "text"), spark.conf.get(KEY_SETTING, None) or OPEN_KEY)
    counts = [(F.size("pii_kinds") - F.size(F.array_remove("pii_kinds", kind))).cast("long").alias(f"n_{kind}") for kind in KINDS]
    return done.select("doc_id", "text", F.size("pii_kinds").cast("long").alias("n_values"), *counts)
