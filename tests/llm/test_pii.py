import hashlib
import random
import re

from segcube.llm import pii, queries
from tests.llm import fixtures as X

BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def fits(kind, match):
    digits = re.sub("[^0-9]", "", match)
    return {"email": lambda: True, "ip": lambda: all(int(p) <= 255 for p in match.split(".")), "card": lambda: 13 <= len(digits) <= 19 and luhn(digits), "phone": lambda: 9 <= len(digits) <= 15}[kind]()


HINTS = {"email": "@", "ip": ".", "phone": "+", "card": ""}  # without them the patterns cannot match; long runs would take plain Python for ever


def base_spans(text):
    return {kind: [(m.start(), m.end()) for m in re.finditer(pattern, text or "") if fits(kind, m[0])] if HINTS[kind] in (text or "") else [] for kind, pattern in BASE.items()}


def base_spans_flat(text):
    return [(k, *s) for k, spans in base_spans(text).items() for s in spans]


def want(doc_id, text):
    spans = base_spans(text)
    joined = ",".join(f"{k}:{a}:{b}" for k in BASE for a, b in spans[k])
    return (doc_id, *(len(spans[k]) for k in BASE), hashlib.sha256(joined.encode()).hexdigest())


def result(df):
    spans = df.pii_spans
    return df.select("doc_id", *(pii.count_of(spans, k) for k in pii.BASE), queries.F.sha2(pii.rendered(pii.base_only(spans)), 256)).collect()


def test_base_spans_equal_brute_force(spark):
    rng, letters = random.Random(2), list("a@.b-1 +(2)3.45-é🙂%_x9")
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(3000)]
    texts += ["".join(rng.choice("0123456789 -.") for _ in range(60)) for _ in range(1000)] + ["a@b.c_x@d.e a@@b.c x@y@z.w", "0001.1.1.1 1.1.1.0256", "4111111111111111"]
    docs = X.awkward_documents(spark)[0].select("doc_id", "text").unionByName(spark.createDataFrame(list(enumerate(texts, 1000)), "doc_id bigint, text string"))
    rows = X.rows_of(docs)
    assert X.multiset(tuple(r) for r in result(pii.find(docs))) == X.multiset(want(d, t) for d, t in rows)


def test_fully_separated_cards_equal_brute_force(spark):
    texts = [s.join(card) for card in ("4111111111111111", "4111111111111112") for s in (" ", "-")] + ["a 4 1-1 1-1 1 1-1 1 1 1 1 1 1 1 1 z", "1 2 3 4 5", "7"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    rows = X.rows_of(docs)
    assert [len(base_spans(t)["card"]) for _, t in rows] == [1, 1, 0, 0, 1, 0, 0]
    assert X.multiset(tuple(r) for r in result(pii.find(docs))) == X.multiset(want(d, t) for d, t in rows)
    masked = pii.find(docs).select("doc_id", pii.masked(queries.F.col("text"), queries.F.col("pii_spans")).alias("m")).collect()
    assert {r.doc_id: r.m for r in masked}[0] == "[CARD]"


def test_added_kinds_need_checksum_or_context(spark):
    texts = ["pay to DE89 3704 0044 0532 0130 00 now", "pay to DE88 3704 0044 0532 0130 00 now", "social security 123-45-6789", "part 123-45-6789", "tel 030 1234 5678", "size 030 1234 5678", "GB82WEST12345698765432"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    got = {r.doc_id: [(s.kind, r.text[s.start : s.end]) for s in r.pii_spans] for r in pii.find(docs).collect()}
    assert [k for k, _ in got[0]] == ["iban"] and not got[1]
    assert got[2] == [("ssn", "123-45-6789")] and not got[3]
    assert got[4] == [("phone_local", "030 1234 5678")] and not got[5]
    assert got[6] == [("iban", "GB82WEST12345698765432")]


def iban(country, account):
    """An account number with its check digits."""
    number = int("".join(str(int(c, 36)) for c in account + country + "00"))
    return f"{country}{98 - number % 97:02d}{account}"


def test_account_numbers_before_capitals_and_each_other(spark):
    spaced, plain, unknown = "DE89 3704 0044 0532 0130 00", "GB82WEST12345698765432", iban("ZZ", "ABCD1234567")
    cases = [
        (f"{spaced} Please pay", [spaced]), (f"{plain} Bank", [plain]), (f"{plain} BIC X", [plain]), (f"{plain} BIC XABCDEFGH 12", [plain]), (f"🙂 {spaced} {plain} NOW", [spaced, plain]),
        (f"SE45 {spaced} OK", [spaced]), (f"{unknown} Please", [unknown]), (f"{unknown} BIC", [unknown]), (f"{plain}X", []), (f"{iban('DE', '1' * 19)} Bank", []), (f"{iban('NO', '86011117947')} A", [iban("NO", "86011117947")]),
    ]
    docs = spark.createDataFrame([(i, text) for i, (text, _) in enumerate(cases)], "doc_id int, text string")
    found = pii.find(docs).withColumn("m", pii.masked(queries.F.col("text"), queries.F.col("pii_spans"))).collect()
    got = {r.doc_id: [r.text[s.start : s.end] for s in r.pii_spans if s.kind == "iban"] for r in found}
    assert got == {i: want for i, (_, want) in enumerate(cases)}
    assert {r.doc_id: r.m for r in found}[2] == "[IBAN] BIC X"


def test_context_raises_the_score(spark):
    docs = spark.createDataFrame([(1, "my card 4111111111111111"), (2, "number 4111111111111111")], "doc_id int, text string")
    got = {r.doc_id: r.pii_spans[0].score for r in pii.find(docs).collect()}
    assert got[1] > got[2]


def test_masking(spark):
    docs = spark.createDataFrame([(1, "é🙂 a@b.cc, then +49 30 1234567!"), (2, None), (3, "nothing"), (4, "4111 1111 1111 1111 a@b.cc")], "doc_id int, text string")
    got = {r.doc_id: r.m for r in pii.find(docs).select("doc_id", pii.masked(queries.F.col("text"), queries.F.col("pii_spans")).alias("m")).collect()}
    assert got == {1: "é🙂 [EMAIL], then [PHONE]!", 2: None, 3: "nothing", 4: "[CARD] [EMAIL]"}


def test_query_and_empty_table(spark):
    got = queries.op2_pii_spans(spark, X.SF).collect()
    assert X.multiset(tuple(r)[:6] for r in got) == X.multiset(want(d, t) for d, t in X.rows_of(X.documents(spark)))
    assert sum(r.n_email + r.n_phone for r in got) > 0
    assert pii.find(X.empty_documents(spark)).count() == 0
