"""Encoding, prefix counts and packing against the libraries themselves."""

import base64
import hashlib
import time
import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from tests.conftest import SMALL
from vecquant.llm import bpe, codec, packing, prefix_counts, queries

JSON, RANKS = public_tokenizers.path(queries.TOKENIZER_FILE), public_tokenizers.path(queries.RANKS_FILE)
ODD = [
    "", " ", "  ", "\n", "a  b", "a   b", "x\n \ny", "x \n y", "x\n\n y", " a ", "x\n", "don't we'll 're !'ve",
    "x\xa0\xa0y \u3000z", "日本 語 🎉🎉 x", "a <|endoftext|> b\n <|endoftext|>", "a\t b", "e\u0301 ß", "0" * 300, "ab" * 200,
]
ROWS = [(i, t) for i, t in enumerate(ODD)] + [(98, None), (99, "twice"), (99, "twice"), (None, "no id")]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(JSON)


@pytest.fixture(scope="module")
def ranked():
    ranks = bpe.read_ranks(RANKS)
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@pytest.fixture(scope="module")
def counter():
    with open(JSON, encoding="utf-8") as file:
        return prefix_counts.PrefixCounter(file.read())


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, "x", 1) for i, t in ROWS], "doc_id long, text string, ids string, n_tokens int")


def test_pattern_is_the_given_one():
    assert bpe.SPLIT_PATTERN == public_tokenizers.PATTERN


def test_codec(spark, odd, ranked):
    rows = codec.encode_documents(odd, RANKS).collect()
    assert len(rows) == len(ROWS)
    texts = defaultdict(list)
    for i, t in ROWS:
        texts[i].append(t or "")
    for r in rows:
        ids = ranked.encode_ordinary(texts[r.doc_id][0])
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id][0].encode()).hexdigest()


def test_decoding_gives_the_texts_back(spark, odd):
    coded = codec.encode_documents(odd, RANKS, keep_ids=True)
    back = {r.doc_id: r.text for r in codec.decode_documents(coded, RANKS).collect()}
    assert all(back[i] == (t or "") for i, t in ROWS)


def test_offsets():
    table = bpe.byte_table(bpe.tokenizer_json(bpe.read_ranks(RANKS)))
    text = "a 🎉 é"
    encoder = bpe.PieceEncoder(bpe.tokenizer_json(bpe.read_ranks(RANKS)))
    ids = np.frombuffer(encoder.encode([text])[0], dtype="<u4")
    spans = codec.token_offsets(text, ids, table)
    assert spans[0] == (0, 1) and spans[-1][1] == len(text) and all(a <= b for a, b in spans)


def test_cache_that_overflows_changes_nothing(library):
    with open(JSON, encoding="utf-8") as file:
        encoder = bpe.PieceEncoder(file.read(), cache_entries=3)
    for t in [*ODD, "a b c d e f g", "h i j a b"]:
        assert np.frombuffer(encoder.encode([t])[0], dtype="<u4").tolist() == library.encode(t, add_special_tokens=False).ids


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet="ab'rels 12\n\t.!é日🎉", max_size=24))
def test_counts_of_all_prefixes(library, counter, text):
    counts = counter.counts(text)
    assert counter.total(text) == len(library.encode(text, add_special_tokens=False).ids)
    for k in range(1, len(text) + 1):
        end = len(text[:k].encode())
        assert counts[end - 1] == len(library.encode(text[:k], add_special_tokens=False).ids)


def test_count_rows(spark, odd, library):
    rows = prefix_counts.count_tokens(odd, JSON, limit=2).collect()
    texts = dict(ROWS)
    assert len(rows) == len(ROWS)
    for r in rows:
        n = len(library.encode(texts[r.doc_id] or "", add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len((texts[r.doc_id] or "").encode()), n, n > 2)


def test_truncation(spark, odd, library):
    texts = dict(ROWS)
    for r in prefix_counts.truncate_to_budget(odd, JSON, 3).collect():
        whole = texts[r.doc_id] or ""
        assert whole.startswith(r.text) and len(library.encode(r.text, add_special_tokens=False).ids) <= 3
        assert all(len(library.encode(whole[:k], add_special_tokens=False).ids) > 3 for k in range(len(r.text) + 1, min(len(whole), len(r.text) + 12) + 1))


def check_packing(rows, ids):
    own, windows = defaultdict(list), defaultdict(list)
    for r in rows:
        own[r.doc_id].append(r)
        windows[r.sequence_id].append(r)
    assert set(own) == set(ids)
    for doc, pieces in own.items():
        full, at = [*ids[doc], 1], 0
        for p in sorted(pieces, key=lambda p: p.start):
            assert p.start == at and p.length > 0 and p.doc_tokens == len(full)
            assert p.ids_crc32 == zlib.crc32(np.array(full[at : at + p.length], "<u4").tobytes())
            at += p.length
        assert at == len(full)
    padded = 0
    for pieces in windows.values():
        at = 0
        for p in sorted(pieces, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 2048
        padded += (2048 - at) if at & (at - 1) else 0
    return padded


def test_packing(spark, library):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    ids = {r.doc_id: library.encode(r.text or "", add_special_tokens=False).ids for r in docs.collect()}
    for parts in (1, 3):
        packed = packing.pack_documents(docs.repartition(parts, "doc_id"), JSON)
        assert check_packing(packed.collect(), ids) <= parts * 2048
    assert packing.padding_report(packed).first().padded_share < 0.03


def test_packing_of_odd_rows(spark, odd, library):
    rows = [(i, t) for i, t in ROWS if i not in (None, 99)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    check_packing(packing.pack_documents(docs, JSON).collect(), {i: library.encode(t or "", add_special_tokens=False).ids for i, t in rows})
    assert packing.pack_documents(odd, JSON).where("doc_id = 99").count() >= 2


def test_empty_tables(spark, odd):
    none = odd.where("doc_id > 1000")
    assert codec.encode_documents(none, RANKS).count() == 0
    assert prefix_counts.count_tokens(none, JSON).count() == 0
    assert packing.pack_documents(none, JSON).count() == 0


@settings(max_examples=50, deadline=None)
@given(st.lists(st.integers(1, 5000), max_size=30), st.integers(1, 40))
def test_packer_fills_every_window_but_one(lengths, waiting):
    packer = packing.TierPacker(0, (256, 512, 1024, 2048), 65_536, waiting)
    for i, n in enumerate(lengths):
        packer.add(i, np.arange(n, dtype="<u4").tobytes())
    packer.fill()
    packer.finish()
    sizes, total = defaultdict(int), defaultdict(int)
    for row in packer.drain():
        sizes[row[5]] += row[2]
        total[row[0]] += row[2]
    assert dict(total) == dict(enumerate(lengths))
    assert sum(n not in (256, 512, 1024, 2048) for n in sizes.values()) <= 1


def test_two_vocabularies_in_one_session(spark, tmp_path, library):
    """Worker processes are reused; what they keep must follow the vocabulary."""
    texts = [(i, f"The answer number {i} isn't known yet.") for i in range(40)]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(2)
    ranks = bpe.read_ranks(RANKS)
    few = {t: r for t, r in ranks.items() if r < 600}
    path, definition = tmp_path / "few.tiktoken", tmp_path / "few.json"
    path.write_text("".join(f"{base64.b64encode(t).decode()} {r}\n" for t, r in few.items()))
    definition.write_text(bpe.tokenizer_json(few))
    small = Tokenizer.from_file(str(definition))
    for _ in range(2):
        for model, ranks_path, json_path in ((library, RANKS, JSON), (small, str(path), str(definition))):
            ids = {i: model.encode(t, add_special_tokens=False).ids for i, t in texts}
            coded = codec.encode_documents(docs, ranks_path, keep_ids=True)
            assert {r.doc_id: r.ids for r in coded.collect()} == ids
            assert {r.doc_id: r.text for r in codec.decode_documents(coded, ranks_path).collect()} == dict(texts)
            assert {r.doc_id: r.n_tokens for r in prefix_counts.count_tokens(docs, json_path).collect()} == {i: len(x) for i, x in ids.items()}
            cut = prefix_counts.truncate_to_budget(docs, json_path, 4).collect()
            assert all(len(model.encode(r.text, add_special_tokens=False).ids) <= 4 for r in cut)
            check_packing(packing.pack_documents(docs, json_path).collect(), ids)


def test_long_texts_are_counted_in_linear_time(counter, library):
    start = time.time()
    letters = "".join(np.random.default_rng(0).choice(list("abcdefghij"), 300_000))
    text = " ".join(letters[k : k + 7] for k in range(0, 300_000, 7)) * 4
    for t in (letters[:20_000], text + "<|endoftext|>" + text, text * 2 + "\n x"):
        assert counter.total(t) == len(library.encode(t, add_special_tokens=False).ids)
    assert counter.total("-" * 200_000) == counter.counts("-" * 200_000)[-1]
    counter.total(letters)
    spaced = counter.counts(text[:400_000])
    assert spaced[-1] == counter.total(text[:400_000]) and time.time() - start < 60


def test_clashing_columns_of_packing(spark):
    docs = spark.createDataFrame([(1, "a b", 5, "x"), (2, None, 6, "y")], "doc_id long, text string, start int, tier string")
    assert sorted((r.doc_id, r.doc_tokens) for r in packing.pack_documents(docs, JSON).collect()) == [(1, 3), (2, 1)]
