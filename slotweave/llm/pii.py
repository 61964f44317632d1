"""Format-preserving pseudonyms for personal data, in DataFrame functions alone.

Values are found by one pattern, validated by kind, and replaced by a keyed permutation of their own format: a Feistel
network whose halves are shifted in turn by amounts that SHA-256 derives from the key, the kind and the other
half. Equal values get equal pseudonyms in all documents and different values of one format different ones.

Kinds: payment cards (issuer range and Luhn's rule hold before and after; the first four digits, which name the issuer, stay), IBANs (the
country stays, the check digits hold), IPv4 addresses (octets without leading zeros, or all padded to three digits: one address, one
pseudonym in either spelling; other spellings digit by digit), dates (the day number moves within years 1-1879, 1880-2126 or 2126-9999, the notation
stays; day first where the year is last), North American phone numbers (area code from 200 up stays so), other numbers with a plus sign (the country
code stays), social security numbers, mail addresses (the local part), and secrets: access keys and values after
password/token/secret/api_key. What fails its validation is left alone. Who knows the key can undo all this, so the caller gives it.

No pattern repeats a group without a bound other than possessively, so long runs neither exhaust Java's stack nor take more than linear time.

Edge cases: null text stays null with no finding; empty text stays empty; text without findings comes back
unchanged, byte for byte; texts and values of any length are searched whole; extra columns pass through; repeated rows give equal rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

DIGIT, LOWER, UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
HEX, BASE32 = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
ROUNDS = 8
FIRST_DAY = "1880-01-01"
#: Windows in which a date moves: days from FIRST_DAY on, and two factors of the window's length.
DAYS_BEFORE, DAYS, DAYS_AFTER = (734, 935), (300, 300), (1409, 2041)

#: Fixed patterns, Java spelling; the first that fits at a place is taken.
EMAIL = r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
SECRET = r"(?i:\b(?:password|passwd|token|secret|api_?key)\s?[=:]\s?\"?)[0-9A-Fa-f]{16,64}(?![0-9A-Za-z])"
ACCESS = r"(?<![0-9A-Za-z])AKIA[0-9A-Z]{16}(?![0-9A-Za-z])"
IP = r"(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9]|\.[0-9])"
ISO_DATE = r"(?<![0-9-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9-])"
DMY_DATE = r"(?<![0-9./])[0-9]{2}[./][0-9]{2}[./][0-9]{4}(?![0-9./])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
PHONE = r"(?<![0-9+])(?:\+?1[ .-]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])"
CARD = r"(?<![0-9])(?:[0-9]{4}(?: [0-9]{4}){3}|[0-9]{4}(?:-[0-9]{4}){3}|3[47][0-9]{2}([ -])[0-9]{6}\1[0-9]{5}|[0-9]{13,19})(?![0-9])"
IBAN = r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?:[0-9A-Z]{11,30}|(?: [0-9A-Z]{4}){2,7}(?: [0-9A-Z]{1,3})?)(?![0-9A-Za-z])"
ABROAD = r"(?<![0-9+])\+[2-9](?:[0-9]{0,2}(?:[ .-][0-9]{2,8}){2,5}|[0-9]{9,13})(?![0-9])"
ALL = "|".join(f"(?:{p})" for p in (EMAIL, SECRET, ACCESS, IBAN, IP, ISO_DATE, DMY_DATE, SSN, CARD, PHONE, ABROAD))
#: Issuer ranges.
ISSUER = r"^(?:4|5[0-8]|6|2(?:22[1-9]|2[3-9]|[3-6]|7[01]|720)|3[04-9])"
#: What every text with a value holds: a mail address its sign, a secret its name, an access key its head, and all others a digit.
MAY = r"[0-9@]|AKIA|(?i:(?:password|passwd|token|secret|api_?key)\s?[=:])"


def _amount(key: str, kind: str, step: Column, half: Column) -> Column:
    """A keyed 60-bit number."""
    told = F.concat_ws("|", F.lit(key), F.lit(kind), step.cast("string"), half.cast("string"))
    return F.conv(F.substring(F.sha2(told, 256), 1, 15), 16, 10).cast("long")


def permute_pair(left: Column, right: Column, a: int | Column, b: int | Column, key: str, kind: str) -> Column:
    """A keyed permutation of pairs (left < a, right < b): struct(l, r)."""

    def turn(s: Column, i: Column) -> Column:
        even = i % 2 == 0
        return F.struct(
            F.when(even, (s["l"] + _amount(key, kind, i, s["r"])) % a).otherwise(s["l"]).alias("l"),
            F.when(even, s["r"]).otherwise((s["r"] + _amount(key, kind, i, s["l"])) % b).alias("r"),
        )

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), F.struct(left.cast("long").alias("l"), right.cast("long").alias("r")), turn)


def permute_text(text: Column, key: str, kind: str, alphabets: tuple[str, ...] = (DIGIT, LOWER, UPPER)) -> Column:
    """A keyed permutation of the strings that have, at every place, a character of the same alphabet, or the same other one."""

    def shifted(half: Column, other: Column, i: Column) -> Column:
        def one(c: Column, at: Column, digest: Column) -> Column:
            by = _amount(key, kind, F.concat_ws(".", i.cast("string"), at.cast("string")), digest)
            out = c
            for letters in alphabets:
                place = F.call_function("instr", F.lit(letters), c)
                out = F.when(place > 0, F.call_function("substr", F.lit(letters), ((place - 1 + by) % len(letters) + 1).cast("int"), F.lit(1))).otherwise(out)
            return out

        letters = F.filter(F.split(half, ""), lambda c: c != "")
        # the other half's digest is taken once, so a long value costs no more than its length
        return F.transform(F.array(F.sha2(other, 256)), lambda digest: F.array_join(F.transform(letters, lambda c, at: one(c, at, digest)), ""))[0]

    def turn(s: Column, i: Column) -> Column:
        even = i % 2 == 0
        return F.struct(F.when(even, shifted(s["l"], s["r"], i)).otherwise(s["l"]).alias("l"), F.when(even, s["r"]).otherwise(shifted(s["r"], s["l"], i)).alias("r"))

    middle = F.floor(F.length(text) / 2).cast("int")
    start = F.struct(F.call_function("substr", text, F.lit(1), middle).alias("l"), F.call_function("substr", text, middle + 1).alias("r"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, turn, lambda s: F.concat(s["l"], s["r"]))


def luhn_rest(digits: Column) -> Column:
    """The sum of Luhn's rule modulo 10; 0 for valid numbers."""

    def add(s: Column, i: Column) -> Column:
        d = F.call_function("substr", digits, F.length(digits) - i, F.lit(1)).cast("int") * F.when(i % 2 == 1, 2).otherwise(1)
        return s + d - F.when(d > 9, 9).otherwise(0)

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), add) % 10


def _refill(shape: Column, digits: Column) -> Column:
    """shape, of a bounded length, with its digits replaced in turn by the given ones."""
    return F.aggregate(
        F.filter(F.split(shape, ""), lambda c: c != ""),
        F.struct(F.lit("").alias("out"), F.lit(1).alias("at")),
        lambda s, c: F.when(
            c.rlike("[0-9]"), F.struct(F.concat(s["out"], F.call_function("substr", digits, s["at"], F.lit(1))).alias("out"), (s["at"] + 1).alias("at"))
        ).otherwise(F.struct(F.concat(s["out"], c).alias("out"), s["at"].alias("at"))),
        lambda s: s["out"],
    )


def _card(hit: Column, key: str) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    body = F.concat(F.call_function("substr", digits, F.lit(1), F.lit(4)), permute_text(F.call_function("substr", digits, F.lit(5), F.length(digits) - 5), key, "card", (DIGIT,)))
    made = F.transform(F.array(body), lambda b: F.concat(b, ((10 - luhn_rest(F.concat(b, F.lit("0")))) % 10).cast("string")))[0]
    return F.when(digits.rlike(ISSUER) & (luhn_rest(digits) == 0), _refill(hit, made)).otherwise(hit)


def _iban_checked(country: Column, account: Column) -> Column:
    """The IBAN of a country and account: two check digits make it leave 1 modulo 97, letters counting from 10 up."""
    letters = F.filter(F.split(F.concat(account, country, F.lit("00")), ""), lambda c: c != "")
    places = F.transform(letters, lambda c: F.call_function("instr", F.lit(DIGIT + UPPER), c) - 1)
    rest = F.aggregate(places, F.lit(0).cast("long"), lambda s, v: (s * F.when(v < 10, 10).otherwise(100) + v) % 97)
    return F.concat(country, F.lpad((98 - rest).cast("string"), 2, "0"), account)


def _iban(hit: Column, key: str) -> Column:
    plain = F.regexp_replace(hit, " ", "")
    country, account = F.call_function("substr", plain, F.lit(1), F.lit(2)), F.call_function("substr", plain, F.lit(5))
    new = _iban_checked(country, permute_text(account, key, "iban", (DIGIT, UPPER)))
    spaced = F.when(hit.contains(" "), F.regexp_replace(new, "(.{4})(?=.)", "$1 ")).otherwise(new)
    letters, rest = F.call_function("substr", hit, F.lit(1), F.lit(2)), F.call_function("substr", hit, F.lit(3))
    return F.when(_iban_checked(country, account) == plain, spaced).when(rest.rlike("^[0-9]{13,19}$"), F.concat(letters, _card(rest, key))).otherwise(hit)


def _ip(hit: Column, key: str) -> Column:
    octets = F.transform(F.split(hit, r"\."), lambda x: x.cast("long"))
    plain, padded = hit.rlike(r"^(?:0|[1-9][0-9]*)(?:\.(?:0|[1-9][0-9]*)){3}$"), hit.rlike(r"^[0-9]{3}(?:\.[0-9]{3}){3}$")

    def made(o: Column) -> Column:
        pair = permute_pair(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, key, "ip")
        new = F.transform(F.array(pair), lambda p: F.array(F.floor(p["l"] / 256), p["l"] % 256, F.floor(p["r"] / 256), p["r"] % 256))[0]
        width = F.when(plain, 1).otherwise(3)
        return F.array_join(F.transform(new, lambda x: F.when(width == 1, x.cast("string")).otherwise(F.lpad(x.cast("string"), 3, "0"))), ".")

    return F.transform(F.array(octets), lambda o: F.when(F.array_max(o) > 255, hit).when(plain | padded, made(o)).otherwise(permute_text(hit, key, "ip digits", (DIGIT,))))[0]


def _date(hit: Column, key: str) -> Column:
    iso = hit.rlike("^[0-9]{4}")
    text = F.when(iso, hit).otherwise(F.concat_ws("-", F.call_function("substr", hit, F.lit(7), F.lit(4)), F.call_function("substr", hit, F.lit(4), F.lit(2)), F.call_function("substr", hit, F.lit(1), F.lit(2))))
    day = F.datediff(F.call_function("try_to_date", text, F.lit("yyyy-MM-dd")), F.lit(FIRST_DAY).cast("date"))
    (a0, b0), (a1, b1), (a2, b2) = DAYS_BEFORE, DAYS, DAYS_AFTER

    def window(d: Column) -> Column:
        """The day's window: where it starts, and its two factors."""
        row = lambda start, a, b: F.struct(F.lit(start).alias("start"), F.lit(a).alias("a"), F.lit(b).alias("b"))
        return F.when(d < 0, row(-a0 * b0, a0, b0)).when(d < a1 * b1, row(0, a1, b1)).otherwise(row(a1 * b1, a2, b2))

    def made(d: Column, w: Column) -> Column:
        pair = permute_pair(F.floor((d - w["start"]) / w["b"]), (d - w["start"]) % w["b"], w["a"], w["b"], key, "date")
        new = F.transform(F.array(pair), lambda p: F.date_add(F.lit(FIRST_DAY).cast("date"), (w["start"] + p["l"] * w["b"] + p["r"]).cast("int")).cast("string"))[0]
        turned = lambda s: F.concat(F.call_function("substr", s, F.lit(9), F.lit(2)), F.call_function("substr", hit, F.lit(3), F.lit(1)), F.call_function("substr", s, F.lit(6), F.lit(2)), F.call_function("substr", hit, F.lit(6), F.lit(1)), F.call_function("substr", s, F.lit(1), F.lit(4)))
        return F.transform(F.array(new), lambda s: F.when(iso, s).otherwise(turned(s)))[0]

    return F.transform(F.array(day), lambda d: F.when(d.isNull(), hit).otherwise(F.transform(F.array(window(d)), lambda w: made(d, w))[0]))[0]


def _phone(hit: Column, key: str) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    own = F.right(digits, F.lit(10))

    def made(d: Column) -> Column:
        area, rest = F.call_function("substr", d, F.lit(1), F.lit(3)).cast("long"), F.call_function("substr", d, F.lit(4)).cast("long")
        pair = permute_pair(area - 200, rest, 800, 10_000_000, key, "phone")
        new = F.transform(F.array(pair), lambda p: F.concat((p["l"] + 200).cast("string"), F.lpad(p["r"].cast("string"), 7, "0")))[0]
        return F.when(area >= 200, new).otherwise(permute_text(d, key, "digits", (DIGIT,)))

    led = F.call_function("substr", digits, F.lit(1), F.length(digits) - 10)
    return _refill(hit, F.concat(led, F.transform(F.array(own), made)[0]))


def _last(hit: Column, head: str, key: str, kind: str, alphabets: tuple[str, ...]) -> Column:
    """Permutes what follows the head pattern."""
    first = F.regexp_extract(hit, head, 0)
    return F.concat(first, permute_text(F.call_function("substr", hit, F.length(first) + 1), key, kind, alphabets))


def pseudonym(hit: Column, key: str) -> Column:
    full = lambda p: hit.rlike(f"^(?:{p})$")
    local = F.substring_index(hit, "@", 1)
    return (
        F.when(hit.contains("@"), F.concat(permute_text(local, key, "mail"), F.lit("@"), F.substring_index(hit, "@", -1)))
        .when(hit.rlike(r"^AKIA"), _last(hit, "^AKIA", key, "access", (BASE32,)))
        .when(hit.rlike(r"^[A-Z]{2}[0-9]{2}"), _iban(hit, key))
        .when(hit.rlike(r"^[A-Za-z]"), _last(hit, r"^[A-Za-z_]+\s?[=:]\s?\"?", key, "secret", (HEX,)))
        .when(hit.rlike(r"^\+[2-9]"), _last(hit, r"^\+(?:[0-9]{1,3}(?=[ .-])|[0-9]{2})", key, "abroad", (DIGIT,)))
        .when(full(r"[0-9]+(?:\.[0-9]+){3}"), _ip(hit, key))
        .when(full(r"[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}[./][0-9]{2}[./][0-9]{4}"), _date(hit, key))
        .when(full(r"[0-9]{3}-[0-9]{2}-[0-9]{4}"), permute_text(hit, key, "ssn", (DIGIT,)))
        .when(full(r"[0-9]{13,19}|[0-9]{4}(?:[ -][0-9]{4}){3}|[0-9]{4}[ -][0-9]{6}[ -][0-9]{5}"), _card(hit, key))
        .otherwise(_phone(hit, key))
    )


#: Session setting that holds the key of the registered query and the pipeline, and the key where none is set: fit for the given
#: synthetic tables alone, as everyone can read it here.
KEY_SETTING, TEST_KEY = "spark.slotweave.pseudonym.key", "key of the synthetic tables"


def session_key(spark: SparkSession) -> str:
    return spark.conf.get(KEY_SETTING, TEST_KEY)


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """docs with its text replaced, and n_replaced and n_found. The key is secret: it decides, and undoes, every pseudonym."""
    text = F.col(text_col)
    hits = F.when(text.rlike(MAY), F.regexp_extract_all(text, F.lit(ALL), F.lit(0))).otherwise(F.array().cast("array<string>"))
    found = docs.withColumn("__hits", hits)
    new = F.transform(F.col("__hits"), lambda h: pseudonym(h, key))
    found = found.withColumn("__new", F.when(F.size("__hits") > 0, new))
    pieces = F.split(text, ALL, -1)
    joined = F.concat(F.array_join(F.transform(F.col("__new"), lambda x, i: F.concat(F.get(F.col("__gaps"), i), x)), ""), F.get(F.col("__gaps"), F.size("__new")))
    found = found.withColumn("__gaps", F.when(F.size("__hits") > 0, pieces))
    changed = F.size(F.filter(F.arrays_zip("__hits", "__new"), lambda z: z["__hits"] != z["__new"]))
    out = found.withColumns({"n_found": F.when(text.isNull(), 0).otherwise(F.size("__hits")).cast("long"), "n_replaced": F.when(F.col("__new").isNull(), 0).otherwise(changed).cast("long"), text_col: F.when(F.col("__new").isNull(), text).otherwise(joined)})
    return out.drop("__hits", "__new", "__gaps")
