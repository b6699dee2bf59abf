import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from segcube.llm import encoding, packing, shared, sstable
from tests.llm import fixtures as X


def plain(name):
    tokenizer = Tokenizer.from_file(encoding.vocabulary(name))
    tokenizer.encode_special_tokens = True
    return tokenizer


@pytest.mark.parametrize(("name", "layout"), [("word_bpe_49k.json", "words"), ("byte_bpe_50k.json", "bytes")])
def test_pieces_encode_like_whole_texts(name, layout):
    rng, letters = random.Random(3), list("ab'sté,.1 \ń  ×日 \tÀß<|")
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 40))) for _ in range(1500)] + ["don't, '' ,'s x's 's I'LL", " x \n\n  y  ", "<|endoftext|>a", None, ""]
    ids, offsets = encoding.Encoder(encoding.vocabulary(name), layout).encode(pa.array(texts))
    for i, made in enumerate(plain(name).encode_batch([t or "" for t in texts], add_special_tokens=False)):
        assert ids[offsets[i] : offsets[i + 1]].tolist() == made.ids, texts[i]


def test_a_full_cache_starts_anew(monkeypatch):
    monkeypatch.setattr(encoding, "CACHE_PIECES", 50)
    one = encoding.Encoder(encoding.vocabulary("word_bpe_49k.json"), "words")
    for n in range(8):
        text = " ".join(f"word{chr(97 + i % 26)}{chr(97 + n)}" for i in range(40))
        assert one.encode(pa.array([text]))[0].tolist() == plain("word_bpe_49k.json").encode(text, add_special_tokens=False).ids


def expected_tokens(rows, name, end):
    tokenizer = plain(name)
    return [(doc_id, text, np.array([*tokenizer.encode(text, add_special_tokens=False).ids, end], dtype="<u4")) for doc_id, text in rows]


def stored(spark, docs):
    manifest = sstable.write_shards(docs, shared.new_folder(spark, "t"), encoding.vocabulary("word_bpe_49k.json"))
    return manifest, sorted(((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in sstable.read_shards(manifest).collect()), key=lambda r: r[1])


@pytest.mark.parametrize("which", ["awkward", "sf"])
def test_shards_hold_every_document_in_order(spark, monkeypatch, which):
    docs = X.awkward_documents(spark)[0] if which == "awkward" else X.documents(spark)
    manifest, got = stored(spark, docs)
    want = expected_tokens(X.rows_of(docs), "word_bpe_49k.json", 1)
    assert [r[0] for r in got] == sorted([d for d, _, _ in want], key=lambda d: (d is not None, d or 0))
    at = 0
    for _, start, n, _ in got:
        assert start == at
        at += n
    assert X.multiset((d, len(i), zlib.crc32(i.tobytes())) for d, _, i in want) == X.multiset((r[0], r[2], r[3]) for r in got)
    ids = [1, 5, 6, 10**9, -4]
    for limit in (sstable.BROADCAST_SHARDS, 0):
        monkeypatch.setattr(sstable, "BROADCAST_SHARDS", limit)
        found = sstable.lookup(manifest, spark.createDataFrame([(i,) for i in ids], "doc_id bigint")).collect()
        assert X.multiset((r.doc_id, tuple(r.ids)) for r in found) == X.multiset((d, tuple(i.tolist())) for d, _, i in want if d in ids)


def test_no_documents_no_shards(spark):
    manifest, got = stored(spark, X.empty_documents(spark))
    assert got == [] and manifest.count() == 0


def test_single_lookups_filter_and_damage(tmp_path):
    path = str(tmp_path / "a" / "x.sst")
    writer = sstable.Writer(path, block_bytes=256)
    rng = np.random.default_rng(1)
    docs = {int(i): rng.integers(0, 49_000, rng.integers(0, 50)).astype(np.uint32) for i in sorted(rng.choice(10_000, 400, replace=False) - 500)}
    for i, ids in docs.items():
        writer.add(sstable.key_of(i), ids)
    writer.close()
    reader = sstable.Reader(path)
    assert len(reader.places) > 20
    with pytest.raises(ValueError, match="does not fit"):
        sstable.Writer(str(tmp_path / "b" / "x.sst")).add(sstable.key_of(1), np.array([5, 1 << 16], dtype=np.uint32))
    for i, ids in docs.items():
        assert [x.tolist() for x in reader.get(i)] == [ids.tolist()]
    absent = [i for i in range(20_000, 24_000)]
    assert all(reader.get(i) == [] for i in absent) and sum(reader.may_hold(i) for i in absent) < 120
    data = bytearray(open(path, "rb").read())
    data[40] ^= 255
    open(path, "wb").write(data)
    with pytest.raises(ValueError, match="checksum"):
        list(sstable.Reader(path).scan())


def check_packing(rows, docs_rows, capacity):
    want = {}
    pieces = []
    for doc_id, _, ids in expected_tokens(docs_rows, "byte_bpe_50k.json", 0):
        n = -(-len(ids) // capacity)
        first = len(ids) - (n - 1) * capacity
        for k in range(n):
            a = 0 if k == 0 else first + (k - 1) * capacity
            b = first + k * capacity
            pieces.append((doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes())))
    assert X.multiset(pieces) == X.multiset((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows)
    for r in rows:
        want.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for places in want.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= capacity
    return len(want), -(-sum(p[3] for p in pieces) // capacity)


@pytest.mark.parametrize("which", ["awkward", "sf"])
def test_packing(spark, which):
    docs = X.awkward_documents(spark)[0] if which == "awkward" else X.documents(spark)
    used, least = check_packing(packing.pack(docs, encoding.vocabulary("byte_bpe_50k.json")).collect(), X.rows_of(docs), 2048)
    assert used <= least * 1.02 + 1


def test_plan_uses_every_piece_once():
    rng = np.random.default_rng(0)
    for n in (0, 1, 500, 20_000):
        histogram = np.bincount(rng.integers(1, 65, n), minlength=65)
        used = np.zeros(65, dtype=int)
        total = 0
        for pattern, repeat in packing.plan(histogram, 64):
            assert sum(pattern) <= 64 and repeat > 0
            total += repeat
            for v in pattern:
                used[v] += repeat
        assert (used == histogram).all()
        assert total <= -(-int((histogram * np.arange(65)).sum()) // 64) * 1.07 + 3


def test_packed_sequences_give_back_every_document(spark):
    docs = X.awkward_documents(spark)[0]
    packed = packing.pack(docs, encoding.vocabulary("byte_bpe_50k.json"))
    found, documents = packing.sequences(packed).collect(), {}
    assert len(found) == packed.select("sequence_id").distinct().count()
    for r in found:
        ids = np.frombuffer(r.ids, dtype="<u4")
        assert len(ids) == r.length == sum(p.length for p in r.pieces) <= 2048
        for p in r.pieces:
            documents.setdefault((p.doc_id, p.start), []).append(ids[p.offset : p.offset + p.length].tolist())
    wanted = {}
    for doc_id, _, ids in expected_tokens(X.rows_of(docs), "byte_bpe_50k.json", 0):
        first = len(ids) - (-(-len(ids) // 2048) - 1) * 2048
        for a, b in zip([0, *range(first, len(ids), 2048)], [*range(first, len(ids) + 1, 2048)], strict=True):
            wanted.setdefault((doc_id, a), []).append(ids[a:b].tolist())
    assert {k: sorted(v) for k, v in documents.items()} == {k: sorted(v) for k, v in wanted.items()}


def test_packing_nothing(spark):
    assert packing.pack(X.empty_documents(spark), encoding.vocabulary("byte_bpe_50k.json")).count() == 0
