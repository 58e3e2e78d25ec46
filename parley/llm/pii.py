"""Personal data replaced by format-preserving pseudonyms, in DataFrame functions only.

One pattern finds candidates; each is validated (check digits, calendar, octets, reserved areas) and then moved by a
keyed Feistel permutation within its own format, so that equal values get equal pseudonyms in every document and table
made with the same key, and different values different ones:

    card numbers   13-19 digits, an issuer's prefix and length, Luhn: what lies between prefix and check digit is permuted
    IBAN           mod 97: the digits after the check digits are permuted, the check digits computed anew
    dates          calendar dates 1900-2099, year first, day first or month first: the day's number is permuted
    social numbers ddd-dd-dddd outside reserved areas: permuted among valid ones
    phone numbers  ten national digits, permuted among valid ones (area and exchange begin with 2-9) or among the others;
                   without country code and brackets only valid ones count; a country code stays
    IPv4           four octets without leading zeros, not a version number: the 32 bits are permuted
    hex secrets    40 hexadecimal digits in one case: the digits are permuted (a commit's name looks alike and is replaced too)
    e-mail         a keyed name at a reserved domain (no permutation: mailboxes have no fixed format)

Candidates that fail validation stay as they are. Where a permutation must stay inside a set (valid dates, phone and
social numbers) it is applied until it lands there again, which keeps it one-to-one. Where kinds overlap, the first in
KINDS wins.

Defined results: null texts stay null and empty ones empty, with 0 replaced; repeated rows are treated alike; very long
texts are searched whole; an empty table gives an empty result; other columns pass through ``pseudonymise`` untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from parley.llm.common import free_name

KEY = "parley-pseudonyms-1"
ROUNDS = 8
WALK = 64
DIGITS, HEX = "0123456789", "0123456789abcdef"

EMAIL = r"(?<![\w.+-])[\w.+-]{1,64}@[\w-]{1,63}(?:\.[\w-]{1,63}){1,5}"
IBAN = r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])"
SECRET = r"(?<![0-9A-Za-z])(?:[0-9a-f]{40}|[0-9A-F]{40})(?![0-9A-Za-z])"
PHONE = r"(?<![\d.+-])(?:\+\d{1,3}[ -]?)?(?:\(\d{3}\) ?|\d{3}[-. ])\d{3}[-. ]\d{4}(?![\d-])"
SOCIAL = r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"
DATE = r"(?<![\d/.-])(?:\d{4}-\d{2}-\d{2}|\d{2}[/.]\d{2}[/.]\d{4})(?![\d/-])"
IP = r"(?<![\d.])(?<!\b[vV])(?<![vV]ersion )\d{1,3}(?:\.\d{1,3}){3}(?!\d|\.\d)"
CARD = r"(?<![\d.-])\d(?:[ -]?\d){12,18}(?!\d)"
#: Prefixes and lengths of card issuers (fixed values): those of one digit, two, three and four digits.
ISSUED = r"^(?:4(?:\d{12}|\d{15}|\d{18})|5[1-5]\d{14}|3[47]\d{13}|6(?:5|2)\d{14,17}|3[689]\d{12,17}|64[4-9]\d{13,16}|30[0-5]\d{11,16}|(?:222[1-9]|22[3-9]\d|2[3-6]\d\d|27[01]\d|2720)\d{12}|6011\d{12,15}|35(?:2[89]|[3-8]\d)\d{12,15})$"
PREFIX = r"^(?:(4)|(5[1-5]|3[47]|6[25]|3[689])|(64[4-9]|30[0-5])|(\d{4}))"
#: In the order in which a place is tried.
KINDS = {"email": EMAIL, "iban": IBAN, "secret": SECRET, "phone": PHONE, "social": SOCIAL, "date": DATE, "ip": IP, "card": CARD}
ANY = "|".join(KINDS.values())
#: A text without any of these holds nothing.
HINT = r"@|\d\D?\d\D?\d|[0-9A-Fa-f]{40}"


def _feistel(s: Column, alphabet: str, tweak: str, key: str) -> Column:
    """s, a string over alphabet, permuted among the strings of its length."""
    half = F.floor(F.length(s) / 2).cast("int")
    begin = F.struct(F.substr(s, F.lit(1), half).alias("a"), F.substr(s, half + 1, F.length(s) - half).alias("b"))

    def turn(x: Column, i: Column) -> Column:
        mixed = F.sha2(F.concat_ws("|", F.lit(key), F.lit(tweak), i.cast("string"), F.length(s).cast("string"), x["b"]), 256)
        shifted = F.transform(
            F.split(x["a"], ""),
            lambda c, k: F.substr(F.lit(alphabet), ((F.instr(F.lit(alphabet), c) - 1 + F.conv(F.substr(mixed, 1 + (2 * k) % 62, F.lit(2)), 16, 10).cast("int")) % len(alphabet) + 1).cast("int"), F.lit(1)),
        )
        return F.struct(x["b"].alias("a"), F.array_join(shifted, "").alias("b"))

    # halves of unequal length swap lengths each turn: an even number of turns brings them back
    return F.when(F.length(s) < 2, s).otherwise(F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), begin, turn, lambda x: F.concat(x["a"], x["b"])))


def _walk(s: Column, good, alphabet: str, tweak: str, key: str) -> Column:
    """Permuted until good again."""
    state = F.struct(_feistel(s, alphabet, tweak, key).alias("s"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), state, lambda x, _: F.when(good(x["s"]), x).otherwise(F.struct(_feistel(x["s"], alphabet, tweak, key).alias("s"))), lambda x: x["s"])


def _digits(v: Column) -> Column:
    return F.regexp_replace(v, r"\D", "")


def _laid_out(v: Column, new: Column) -> Column:
    """v with its digits replaced in order by those of new."""
    step = lambda x, c: F.when(c.rlike(r"\d"), F.struct((x["n"] + 1).alias("n"), F.concat(x["out"], F.substr(new, x["n"], F.lit(1))).alias("out"))).otherwise(F.struct(x["n"].alias("n"), F.concat(x["out"], c).alias("out")))
    return F.aggregate(F.split(v, ""), F.struct(F.lit(1).alias("n"), F.lit("").alias("out")), step, lambda x: x["out"])


def _luhn_sum(d: Column) -> Column:
    """Luhn's sum of a number's digits, the last one being the check digit."""
    twice = F.transform(F.split(F.reverse(d), ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(2 * c.cast("int") - F.when(c.cast("int") > 4, F.lit(9)).otherwise(F.lit(0))))
    return F.aggregate(twice, F.lit(0), lambda a, b: a + b)


def _mod97(s: Column) -> Column:
    code = lambda c: F.when(c.rlike("[0-9]"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    return F.aggregate(F.split(s, ""), F.lit(0), lambda a, c: (a * F.when(c.rlike("[0-9]"), F.lit(10)).otherwise(F.lit(100)) + code(c)) % 97)


def card(v: Column, key: str) -> Column:
    d = _digits(v)
    head = F.regexp_extract(d, PREFIX, 0)
    body = F.concat(head, _feistel(F.substr(d, F.length(head) + 1, F.length(d) - F.length(head) - 1), DIGITS, "card", key))
    new = F.concat(body, ((10 - _luhn_sum(F.concat(body, F.lit("0"))) % 10) % 10).cast("string"))
    return F.when(d.rlike(ISSUED) & (_luhn_sum(d) % 10 == 0), _laid_out(v, new))


def iban(v: Column, key: str) -> Column:
    plain = F.regexp_replace(v, " ", "")
    body = F.substr(plain, F.lit(5), F.length(plain) - 4)
    moved = _laid_out(body, _feistel(_digits(body), DIGITS, "iban", key))
    country = F.substr(plain, F.lit(1), F.lit(2))
    check = F.lpad((98 - _mod97(F.concat(moved, country, F.lit("00")))).cast("string"), 2, "0")
    fresh = F.concat(country, check, moved)
    spaced = F.aggregate(F.split(v, ""), F.struct(F.lit(1).alias("n"), F.lit("").alias("out")), lambda x, c: F.when(c == " ", F.struct(x["n"].alias("n"), F.concat(x["out"], c).alias("out"))).otherwise(F.struct((x["n"] + 1).alias("n"), F.concat(x["out"], F.substr(fresh, x["n"], F.lit(1))).alias("out"))), lambda x: x["out"])
    return F.when(_mod97(F.concat(body, F.substr(plain, F.lit(1), F.lit(4)))) == 1, spaced)


def secret(v: Column, key: str) -> Column:
    moved = _feistel(F.lower(v), HEX, "secret", key)
    return F.when(v == F.lower(v), moved).otherwise(F.upper(moved))


def phone(v: Column, key: str) -> Column:
    d = _digits(v)
    head = F.length(d) - 10
    national = F.substr(d, head + 1, F.lit(10))
    valid = lambda s: s.rlike(r"^[2-9]\d\d[2-9]")
    moved = _walk(national, lambda s: valid(s) == valid(national), DIGITS, "phone", key)
    return F.when(v.rlike(r"[+(]") | valid(national), _laid_out(v, F.concat(F.substr(d, F.lit(1), head), moved)))


def _valid_social(d: Column) -> Column:
    return ~d.rlike(r"^(000|666|9)|^...00|0000$")


def social(v: Column, key: str) -> Column:
    return F.when(_valid_social(_digits(v)), _laid_out(v, _walk(_digits(v), _valid_social, DIGITS, "social", key)))


def _date(v: Column, pattern: str, good, key: str) -> Column:
    """A calendar date between 1900 and 2099, moved among those that good() accepts."""
    first, days = F.to_date(F.lit("1900-01-01")), 73049
    day = F.try_to_date(F.regexp_replace(v, r"\.", "/"), pattern)
    back = lambda s: F.date_add(first, s.cast("int"))
    inside = lambda s: (s.cast("int") < days) & F.coalesce(good(back(F.least(s.cast("int"), F.lit(days)))), F.lit(False))
    number = F.lpad(F.date_diff(day, first).cast("string"), 5, "0")
    moved = F.date_format(back(_walk(number, inside, DIGITS, f"date {pattern}", key)), pattern)
    return F.when(F.year(day).between(1900, 2099) & good(day), F.when(v.contains("."), F.regexp_replace(moved, "/", ".")).otherwise(moved))


def date(v: Column, key: str) -> Column:
    return F.coalesce(
        F.when(v.contains("-"), _date(v, "yyyy-MM-dd", lambda d: F.lit(True), key)),
        F.when(~v.contains("-"), _date(v, "dd/MM/yyyy", lambda d: F.lit(True), key)),
        F.when(~v.contains("-"), _date(v, "MM/dd/yyyy", lambda d: F.dayofmonth(d) > 12, key)),
    )


def ip(v: Column, key: str) -> Column:
    octet = F.split(v, r"\.")
    bits = F.array_join(F.transform(octet, lambda x: F.lpad(F.lower(F.hex(x.cast("long"))), 2, "0")), "")
    moved = _feistel(bits, HEX, "ip", key)
    part = lambda k: F.conv(F.substr(moved, F.lit(1 + 2 * k), F.lit(2)), 16, 10)
    return F.when(F.forall(octet, lambda x: (x.cast("int") < 256) & ~x.rlike("^0.")), F.concat_ws(".", *[part(k) for k in range(4)]))


def email(v: Column, key: str) -> Column:
    return F.concat(F.lit("u"), F.substr(F.sha2(F.concat_ws("|", F.lit(key), F.lit("email"), F.lower(v)), 256), F.lit(1), F.lit(20)), F.lit("@example.invalid"))


def pseudonym(v: Column, key: str = KEY) -> Column:
    """A candidate's pseudonym; null if it isn't valid."""
    makers = {"email": email, "iban": iban, "secret": secret, "phone": phone, "social": social, "date": date, "ip": ip, "card": card}
    out = None
    for kind, pattern in KINDS.items():
        whole = v.rlike(f"^(?:{pattern})$")
        out = F.when(whole, makers[kind](v, key)) if out is None else out.when(whole, makers[kind](v, key))
    return out


def pseudonymise(df: DataFrame, text_col: str = "text", key: str = KEY) -> DataFrame:
    """df with its texts rewritten, and n_replaced (long; it takes the place of a column of that name)."""
    text, seen, fresh = F.col(text_col), free_name(df, "pii_found"), free_name(df, "pii_new")
    step = df.withColumn(seen, F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))))
    step = step.withColumn(fresh, F.when(F.size(seen) > 0, F.transform(seen, lambda v: pseudonym(v, key))))
    pieces = F.split(text, ANY)
    joined = F.array_join(F.zip_with(pieces, F.zip_with(seen, fresh, lambda v, n: F.coalesce(n, v)), lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
    return step.withColumns({text_col: F.when(F.size(seen) > 0, joined).otherwise(text), "n_replaced": F.coalesce(F.size(F.filter(fresh, lambda n: n.isNotNull())), F.lit(0)).cast("long")}).drop(seen, fresh)
