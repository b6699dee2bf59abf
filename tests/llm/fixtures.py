"""Small tables with every awkward case: nulls, empty and long texts, ties, repeated rows, extra columns with clashing names."""

import random

SF = "/root/testdata/sf0.001"


def words(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


def awkward_documents(spark):
    rng = random.Random(7)
    base = words(rng, 60)
    near = base.split()
    near[30] = "changed"
    item = words(random.Random(11), 14)
    texts = [
        None, "", "   \n\t ", "one", "two words", "a b c d e", base, base, " ".join(near), base.upper(), words(rng, 30_000), "x" * 300_000, "1" * 70_000, "a@" * 3000,
        f"see {item} there", f"Mail me: jo.do@mail.example.com, or x@y.zz_q@a.b; 10.0.0.1 and 999.1.1.1 300.1.2.3.4.5", "card 4111 1111 1111 1111 or 4111-1111-1111-1112 phone +49 (30) 1234-567 and +1 2",
        "IBAN DE89 3704 0044 0532 0130 00 ok; DE88 3704 0044 0532 0130 00 no; social security 123-45-6789", "this is under the GNU General Public License, and the Apache License; cc by. MIT License mit license",
        "é ß ẞ ſ 日本語 テスト nbsp don't 'll 12ab34 <|endoftext|>", "taiĺ \x0b\x0c\x1c z", "the idiot moron scum is trash", "🙂 +49 30 1234567 a@b.cc 🙂",
    ]
    rows = [(i, t, "en", "s", 1, "clash", 5) for i, t in enumerate(texts)]
    rows += [(6, base, "en", "s", 1, "clash", 5), (None, base, None, None, None, None, None), (None, None, None, None, None, None, None), (7, "other text with the same id", "de", "s", 1, "c", 5)]
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words string, n long"
    return spark.createDataFrame(rows, schema).repartition(3), item


def empty_documents(spark):
    return spark.createDataFrame([], "doc_id bigint, text string, lang string, source string, n_chars bigint")


def documents(spark, sf=SF):
    return spark.read.parquet(f"{sf}/documents.parquet")


def rows_of(df):
    return [(r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()]


def multiset(rows):
    return sorted(rows, key=repr)
