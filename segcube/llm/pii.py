r"""Personal data: patterns propose spans, checksums confirm them, words nearby adjust the score.  DataFrame operations only.

For each kind a pattern cuts the whole text once; the lengths of what lies between matches give their places in
code points.  Cards must pass the Luhn test, account numbers (IBAN) the test modulo 97, addresses the range of their
parts, phones the number of their digits; failing matches are dropped.  Kinds beyond the four base kinds are kept
only from a score of ``MIN_SCORE`` on, which context words raise.

A null or empty text has no spans; texts of any length are read whole; repeated rows are read one by one; an empty
table gives no rows.  Patterns use possessive repeats, so a very long run of digits or letters costs no stack and no
backtracking.

Account numbers are looked for at every possible start, also inside a candidate that fails.  The first two letters decide the length; for
letters without a known one, ends at word borders are tried, longest first, until the test modulo 97 holds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Kinds in their order, a hint that a text must hold to be searched, and patterns.  The patterns match what
# the agreed ones match; \G and the look-behind only keep a start inside a run from being tried in vain.
_LOCAL = r"[A-Za-z0-9._%+-]"
# Account-number countries by the number of characters.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA", 23: "AE GI IL IQ OM SO TL",
    24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HN HU LB NI PL SV", 29: "BR EG PS QA UA", 30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}
_KNOWN = "|".join(IBAN_LENGTHS.values()).replace(" ", "|")
_ACCOUNTS = "|".join(rf"(?:{c.replace(' ', '|')})[0-9]{{2}}(?:\x20?[A-Z0-9]){{{n - 4}}}" for n, c in IBAN_LENGTHS.items()) + rf"|(?!{_KNOWN})[A-Z]{{2}}[0-9]{{2}}(?:\x20?[A-Z0-9]){{11,30}}"
KINDS = {
    "email": ("@", rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": (".", r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}+"),
    "card": (None, r"[0-9](?:[\x20-]?[0-9]){12,}+"),
    "phone": ("+", r"\+[0-9][\x20().0-9-]+[0-9]"),
    "iban": (None, rf"(?<![A-Za-z0-9])(?=[A-Z]{{2}}[0-9]{{2}})(?=((?:{_ACCOUNTS})(?![A-Za-z0-9])))[A-Z0-9]{{4}}"),
    "ssn": ("-", r"(?<![0-9A-Za-z-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9A-Za-z-])"),
    "phone_local": (None, r"(?<![0-9A-Za-z+(.-])\(?[0-9]{2,4}\)?(?:[\x20.-][0-9]{2,4}){2,4}+(?![0-9A-Za-z-])"),
}
BASE = ("email", "ip", "card", "phone")
#: Kinds whose pattern gives the match as its first group and takes only so many code points, so that matches may overlap.
AHEAD = {"iban": 4}
# Score of a confirmed span, score added by context, and the context words.
SCORES = {
    "email": (0.9, 0.1, "e-?mail|mail|contact|write"),
    "ip": (0.6, 0.3, "ip|host|server|address|login"),
    "card": (0.7, 0.3, "card|visa|mastercard|amex|credit|payment|karte|carte|tarjeta"),
    "phone": (0.7, 0.3, "phone|tel|telephone|call|mobile|fax|telefon|téléphone|teléfono"),
    "iban": (0.9, 0.1, "iban|account|bank|konto|compte|cuenta"),
    "ssn": (0.4, 0.4, "ssn|social|security"),
    "phone_local": (0.2, 0.5, "phone|tel|telephone|call|mobile|fax|telefon|téléphone|teléfono"),
}
MIN_SCORE = 0.6
#: Code points before and after a span in which context words count.
CONTEXT = 40
SPAN = "struct<kind:string,start:bigint,end:bigint,score:double>"


def digits_of(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def luhn_ok(digits: Column) -> Column:
    """The Luhn checksum of a string of digits."""

    def add(total: Column, place: Column) -> Column:
        digit = digits.substr(F.length(digits) - place, F.lit(1)).cast("int")
        twice = digit * 2
        return total + F.when(place % 2 == 0, digit).when(twice > 9, twice - 9).otherwise(twice)

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), add) % 10 == 0


def mod97_ok(account: Column) -> Column:
    """The check of an account number: its first four characters moved to the end, letters as 10 to 35, is 1 modulo 97."""
    plain = F.regexp_replace(account, "\\x20", "")
    moved = F.concat(plain.substr(F.lit(5), F.length(plain)), plain.substr(1, 4))

    def add(rest: Column, char: Column) -> Column:
        code = F.ascii(char)
        return F.when(code < 58, (rest * 10 + code - 48) % 97).otherwise((rest * 100 + code - 55) % 97)

    return F.aggregate(F.split(moved, "(?<=.)(?=.)"), F.lit(0), add) == 1


def account(match: Column) -> Column:
    """The part of a match, from its start, that passes the test modulo 97; null if none."""
    words = F.split(match, "\\x20")
    ends = F.transform(F.sequence(F.size(words), F.lit(1), F.lit(-1)), lambda n: F.array_join(F.slice(words, 1, n), " "))
    shorter = F.filter(ends, lambda part: (F.length(F.regexp_replace(part, "\\x20", "")) >= 15) & mod97_ok(part))
    return F.when(match.rlike(f"^(?:{_KNOWN})"), F.when(mod97_ok(match), match)).otherwise(F.get(shorter, F.lit(0)))


def _confirmed(kind: str, match: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(match, r"\."), lambda part: part.rlike("^0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])$"))
    if kind == "card":
        return F.length(digits_of(match)).between(13, 19) & luhn_ok(digits_of(match))
    if kind == "phone":
        return F.length(digits_of(match)).between(9, 15)
    if kind == "phone_local":
        return F.length(digits_of(match)).between(7, 12)
    return F.lit(True)


def _span_text(kind: str, match: Column) -> Column:
    """What of a match is a span; null if nothing."""
    return account(match) if kind == "iban" else F.when(_confirmed(kind, match), match)


def _cut(text: Column, kind: str) -> Column:
    """Matches of a kind and the pieces between them, read only where the text can hold any."""
    hint, pattern = KINDS[kind]
    found = F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(int(kind in AHEAD))).alias("matches"), F.split(text, pattern, -1).alias("pieces"))
    may = text.contains(hint) if hint else text.rlike(r"[0-9][\x20-]?[0-9]" if kind == "card" else "[0-9]{2}")
    return F.when(may, found)


def _spans(cut: Column, kind: str) -> Column:
    """Confirmed spans of a kind in order of their start, from :func:`_cut`."""
    score, more, words = SCORES[kind]
    matches, pieces = cut["matches"], cut["pieces"]
    taken = lambda match: F.lit(AHEAD[kind]) if kind in AHEAD else F.length(match)
    steps = F.zip_with(F.slice(pieces, 1, F.size(matches)), matches, lambda piece, match: F.struct(F.length(piece).cast("bigint").alias("gap"), taken(match).cast("bigint").alias("size")))
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<bigint>").alias("starts"))
    starts = F.aggregate(steps, start, lambda a, s: F.struct((a["at"] + s["gap"] + s["size"]).alias("at"), F.concat(a["starts"], F.array(a["at"] + s["gap"])).alias("starts")), lambda a: a["starts"])

    def span(match: Column, i: Column) -> Column:
        found = _span_text(kind, match)
        after = F.substring(F.get(pieces, i + 1), F.length(found) - AHEAD[kind] + 1, F.lit(CONTEXT)) if kind in AHEAD else F.left(F.get(pieces, i + 1), F.lit(CONTEXT))
        near = F.lower(F.concat_ws(" ", F.right(F.get(pieces, i), F.lit(CONTEXT)), after))
        value = F.lit(score) + F.when(near.rlike(rf"(?:^|[^\p{{L}}])(?:{words})(?:$|[^\p{{L}}])"), more).otherwise(0.0)
        ends = F.get(starts, i) + F.length(found)
        return F.when(found.isNotNull(), F.struct(F.lit(kind).alias("kind"), F.get(starts, i).alias("start"), ends.alias("end"), value.alias("score")))

    spans = F.filter(F.transform(matches, span), lambda s: s.isNotNull() if kind in BASE else s.isNotNull() & (s["score"] >= MIN_SCORE))
    some = F.when(F.size(matches) > 0, spans)
    return F.coalesce(some, F.array().cast(f"array<{SPAN}>")).cast(f"array<{SPAN}>")


def find(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with a column ``pii_spans``: all spans by kind, then start (code points, end exclusive)."""
    out = docs.withColumn("_pii_text", F.coalesce(F.col(text_col), F.lit("")))
    for kind in KINDS:
        out = out.withColumn(f"_pii_{kind}", _cut(F.col("_pii_text"), kind))
    out = out.withColumn("pii_spans", F.concat(*(_spans(F.col(f"_pii_{kind}"), kind) for kind in KINDS)))
    return out.drop("_pii_text", *(f"_pii_{kind}" for kind in KINDS))


def rendered(spans: Column) -> Column:
    """``kind:start:end`` of each span, joined by commas."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def count_of(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("bigint")


def base_only(spans: Column) -> Column:
    return F.filter(spans, lambda s: s["kind"].isin(*BASE))


def masked(text: Column, spans: Column) -> Column:
    """The text with each span, overlapping ones together, replaced by the first one's kind in brackets."""
    init = F.struct(F.lit(0).cast("bigint").alias("at"), F.lit("").alias("out"))

    def step(a: Column, s: Column) -> Column:
        fresh = F.concat(a["out"], F.substring(text, (a["at"] + 1).cast("int"), (s["start"] - a["at"]).cast("int")), F.lit("["), F.upper(s["kind"]), F.lit("]"))
        return F.struct(F.greatest(a["at"], s["end"]).alias("at"), F.when(s["start"] >= a["at"], fresh).otherwise(a["out"]).alias("out"))

    ordered = F.sort_array(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    whole = F.aggregate(ordered, init, step, lambda a: F.concat(a["out"], F.substring(text, (a["at"] + 1).cast("int"), F.lit(2**31 - 1))))
    return F.when(F.size(spans) > 0, whole).otherwise(text)
