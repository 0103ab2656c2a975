"""Digests, simhash, components and the pipeline: brute force and odd rows."""

import hashlib
import math
import re
import tracemalloc
from collections import Counter

import numpy as np
import pytest
import xxhash

from tests.conftest import MIDDLE, SMALL
from vecquant.llm import feature_digest, simhash
from vecquant.llm.components import smallest_reachable


def near(codes, limit=4):
    """Least member of each code's component, by all pairs."""
    a, parent = np.array(codes, dtype=np.uint64), np.arange(len(codes))
    for i in range(len(a)):
        for j in np.flatnonzero(np.bitwise_count(a[i] ^ a[i + 1 :]) <= limit) + i + 1:
            x, y = simhash._find(parent, i), simhash._find(parent, j)
            if x != y:
                parent[max(x, y)] = min(x, y)
    return [simhash._find(parent, i) for i in range(len(a))]


def plain_print(text, width=4):
    words = re.findall(r"[^\x20\x09-\x0D]+", text.translate({i: i + 32 for i in range(65, 91)}))
    shingles = [" ".join(words[i : i + width]) for i in range(len(words) - width + 1)] or ([" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_near_duplicates_match_all_pairs(spark):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    ids = sorted(texts)
    prints = {d: plain_print(texts[d] or "") for d in ids}
    least = dict(zip(ids, [ids[k] for k in near([prints[d] for d in ids])], strict=True))
    rows = simhash.near_duplicates(docs).collect()
    assert len(rows) == len(ids)
    assert all(r.fingerprint == f"{prints[r.doc_id]:016x}" and r.component_id == least[r.doc_id] for r in rows)
    kept = simhash.keep_one_per_group(docs)
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == sorted(set(least.values()))


def test_near_duplicates_of_odd_rows(spark):
    rows = [(5, None), (6, ""), (7, " "), (8, "one"), (9, "ONE"), (9, "ONE"), (10, "completely other words in this text here"), (11, "a b c d e f g h i j"), (None, "one"), (10, "a b c d e f g h i j")]
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, code int")
    found = simhash.near_duplicates(docs).collect()
    assert len(found) == len(rows)
    by = {}
    for r in found:
        by.setdefault(r.doc_id, set()).add(r.component_id)
    assert by[5] == by[6] == by[7] == {5} and by[8] == by[9] == {8} == by[None] and by[10] == by[11] == {10}
    assert sorted(r.doc_id for r in simhash.keep_one_per_group(docs).collect()) == [5, 8, 10]
    assert simhash.near_duplicates(docs.where("doc_id > 99")).count() == 0
    nameless = spark.createDataFrame([(None, "p q r s t"), (None, "p q r s t"), (None, "quite another one")], "doc_id long, text string")
    assert simhash.keep_one_per_group(nameless).count() == 2


@pytest.mark.parametrize("node_rows", [20_000, 40])
def test_links_keep_dense_groups_together(spark, node_rows):
    rng = np.random.default_rng(0)
    codes = set()
    for b in rng.integers(0, 2**63, 3, dtype=np.uint64):
        for _ in range(300):
            v = int(b)
            for k in rng.integers(0, 64, rng.integers(0, 7)):
                v ^= 1 << int(k)
            codes.add(v)
    codes = sorted(codes)
    signed = [int(np.uint64(v).astype(np.int64)) for v in codes]
    links = simhash.link_codes(spark.createDataFrame([(v,) for v in signed], "code long"), node_rows=node_rows).collect()
    place, parent = {v: i for i, v in enumerate(signed)}, np.arange(len(codes))
    for r in links:
        assert (np.uint64(codes[place[r.a]]) ^ np.uint64(codes[place[r.b]])).item().bit_count() <= 4
        x, y = simhash._find(parent, place[r.a]), simhash._find(parent, place[r.b])
        parent[max(x, y)] = min(x, y)
    assert [simhash._find(parent, i) for i in range(len(codes))] == near(codes)


def test_components(spark):
    chain = spark.range(200).selectExpr("id a", "id + 1 b").unionByName(spark.createDataFrame([(900, 901), (901, 900), (7, 7), (950, 901)], "a long, b long"))
    found = {r.node: r.component for r in smallest_reachable(chain).collect()}
    assert found == {**dict.fromkeys(range(201), 0), 900: 900, 901: 900, 950: 900}
    assert smallest_reachable(chain.where("a > 5000")).count() == 0


def plain_bins(raw):
    """Entropy bins by counting every window anew, in exact steps of the module's unit."""
    out = []
    for i in range(len(raw) - 63):
        total = sum(round(c * math.log2(c) * (1 << 20)) for c in Counter(raw[i : i + 64]).values())
        out.append(max(0, (6 * 64 * (1 << 20) - total) // (1 << 20)))
    return out


def plain_digest(text, ranks):
    """Filters of one text by plain loops: (filter, bit) pairs and the number of filters."""
    raw = text.encode()
    if not raw:
        return set(), 0
    raw = raw.ljust(64, b"\0")
    bins = plain_bins(raw)
    wins = Counter()
    for i in range(len(bins)):
        wins[min(range(i, min(i + 64, len(bins))), key=lambda j: (ranks[bins[j]], j))] += 1
    least = min(16, max(wins.values()))
    features = []
    for j in sorted(wins):
        if wins[j] < least:
            continue
        h = 0x9E3779B97F4A7C15
        for k in range(0, 64, 8):
            h = ((h ^ int.from_bytes(raw[j + k : j + k + 8], "little")) * 0xFF51AFD7ED558CCD) % 2**64
            h ^= h >> 29
        h = (h * 0xC4CEB9FE1A85EC53) % 2**64
        h ^= h >> 32
        if h not in features:
            features.append(h)
    return {(n // 160, h >> 11 * k & 2047) for n, h in enumerate(features) for k in range(5)}, -(-len(features) // 160)


def test_digests_match_plain_loops(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    texts = [r.text or "" for r in docs.collect()]
    histogram = Counter(b for t in texts for b in plain_bins(t.encode()))
    ranks = feature_digest.measure_rarity(docs)
    # Windows over two texts count too, so only the order of clearly apart bins is fixed.
    common = max(histogram, key=histogram.get)
    assert ranks[common] > 350 and sorted(ranks.tolist()) == list(range(feature_digest.BINS))
    some = [t for t in texts if len(t) < 3000][:25] + ["", "x", "ab" * 400, "é" * 40, "".join(map(chr, range(32, 700)))]
    for t, digest in zip(some, feature_digest.digests(some, ranks), strict=True):
        bits, n = plain_digest(t, ranks)
        found = np.unpackbits(digest, axis=1) if len(digest) else np.zeros((0, 2048))
        assert len(digest) == n and {(int(a), int(b)) for a, b in zip(*np.nonzero(found), strict=True)} == bits


def test_long_texts_are_digested_in_blocks(monkeypatch):
    ranks = feature_digest.usual_ranks()
    text = "".join(np.random.default_rng(4).choice(list("abcdefgh ij\n"), 40_000)) + "z" * 5_000
    whole = feature_digest.digests([text, "x" * 9_000, "short"], ranks)
    monkeypatch.setattr(feature_digest, "_LONG", 1_000)
    blocks = feature_digest.digests([text, "x" * 9_000, "short"], ranks)
    assert all(np.array_equal(a, b) for a, b in zip(whole, blocks, strict=True)) and len(whole[0]) > 3


def test_a_very_long_text_takes_bounded_memory():
    ranks, text = feature_digest.usual_ranks(), "".join(np.random.default_rng(5).choice(list("abcdefgh ij\n"), 1 << 20)) * 50
    tracemalloc.start()
    assert len(feature_digest.digests([text], ranks)[0]) > 100
    assert tracemalloc.get_traced_memory()[1] < 600_000_000  # the text's bytes are 52 million
    tracemalloc.stop()


def test_entropy_bins():
    raw = np.random.default_rng(1).integers(97, 110, 70_000).astype(np.uint8)
    bins = feature_digest.entropy_bins(raw)
    for i in (0, 1, 63, 65_472, 65_536, 69_936):
        assert plain_bins(raw[i : i + 64].tobytes()) == [bins[i]]


@pytest.mark.parametrize("range_bytes", [24_000_000, 20_000])
def test_digests_and_edits(spark, range_bytes):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    order = sorted(((r.doc_id, r.text or "") for r in docs.collect()), reverse=True)
    after = {d: order[(i + 1) % len(order)][1] for i, (d, _) in enumerate(order)}
    texts = dict(order)
    ranks = feature_digest.measure_rarity(docs)
    rows = feature_digest.edit_sensitivity(docs, range_bytes=range_bytes).collect()
    assert sorted(r.doc_id for r in rows) == sorted(texts)
    for r in rows:
        t = texts[r.doc_id]
        edited = t[: len(t) - len(t) // 2] + after[r.doc_id][: len(t) // 2]
        own, changed, other = feature_digest.digests([t, edited, after[r.doc_id]], ranks)
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert (r.fingerprint, r.edited_fingerprint) == (feature_digest.fingerprint_text(own), feature_digest.fingerprint_text(changed))
        assert r.near_edited == feature_digest.likeness(own, changed) and r.near_next == feature_digest.likeness(own, other)
    long_ones = [r for r in rows if r.n_chars > 1000]
    assert np.mean([r.near_edited > r.near_next for r in long_ones]) > 0.97


def test_digests_of_odd_rows(spark):
    rows = [(3, None), (2, ""), (1, "x" * 10_000), (1, "x" * 10_000), (None, "short"), (None, None), (0, "été " * 50)]
    docs = spark.createDataFrame([(i, t, "f") for i, t in rows], "doc_id long, text string, fingerprint string")
    found = feature_digest.edit_sensitivity(docs).collect()
    assert len(found) == len(rows)
    assert len({r.fingerprint for r in found if r.doc_id == 1}) == 1 and all(0 <= r.near_next <= 1 for r in found)
    assert feature_digest.edit_sensitivity(docs.where("doc_id = 0")).first().near_next == 1
    assert feature_digest.edit_sensitivity(docs.where("doc_id > 99")).count() == 0
    assert feature_digest.fingerprint_documents(docs).count() == len(rows)


def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{MIDDLE}/labels.parquet").collect()}
    before = {r.doc_id for r in docs.select("doc_id").collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, MIDDLE).collect(), docs.schema)
        now = {r.doc_id for r in docs.select("doc_id").collect()}
        assert now < before, name
        if "quality classifier" in name:
            assert np.mean([labels[d] == 1 for d in now if d in labels]) > 0.99
        before = now
    texts = [r.text for r in docs.collect()]
    assert near([plain_print(t) for t in texts]) == list(range(len(texts)))
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, MIDDLE)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == before
    whole = corpus_pipeline.run(spark, MIDDLE)
    assert {r.doc_id for r in whole.select("doc_id").distinct().collect()} == before


def word_sets(texts):
    out = []
    for t in texts:
        w = t.encode().lower().split()
        out.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    return out


@pytest.mark.parametrize("chunk", [2_000_000, 300])
def test_pipeline_dedup_links_all_similar_pairs(spark, chunk, monkeypatch):
    import corpus_pipeline
    from vecquant.llm import shingles

    monkeypatch.setattr(shingles.links, "__defaults__", ("text", chunk))
    rng, rows = np.random.default_rng(3), []
    for g in range(6):
        base = [f"w{x}" for x in rng.integers(0, 5000, 150)]
        for c in range(12):
            w = list(base)
            for at in rng.choice(150, c % 5, replace=False):  # about 0.97 to 0.75 alike
                w[at] = f"x{rng.integers(0, 10**6)}"
            rows.append((100 * g + c, " ".join(w)))
    rows += [(900, ""), (901, None), (902, "a b"), (903, "A  b"), (904, "a c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets, parent = word_sets([t or "" for _, t in rows]), np.arange(len(rows))
    for i, a in enumerate(sets):
        for j in range(i + 1, len(sets)):
            if a == sets[j] or len(a & sets[j]) >= 0.8 * len(a | sets[j]):
                x, y = simhash._find(parent, i), simhash._find(parent, j)
                parent[max(x, y)] = min(x, y)
    least = {rows[i][0]: rows[simhash._find(parent, i)][0] for i in range(len(rows))}
    found = {r.doc_id: r.component_id for r in simhash.similar_documents(docs).collect()}
    assert found == least
    kept = corpus_pipeline.near_duplicates(spark, docs, SMALL).collect()
    assert sorted(r.doc_id for r in kept) == sorted(set(least.values()))


def test_pipeline_stages_of_odd_rows(spark):
    import corpus_pipeline

    good = {r.doc_id: r.text for r in spark.read.parquet(f"{SMALL}/documents.parquet").where("n_chars between 1000 and 2000 and lang = 'en'").limit(3).collect()}
    texts = list(good.values())
    rows = [(1, texts[0]), (1, texts[0]), (2, texts[0]), (None, texts[1]), (None, texts[1]), (5, None), (6, ""), (7, "x" * 30_000), (8, texts[2]), (8, texts[1] + " more words at the end")]
    schema = "doc_id long, text string, lang string, source string, n_chars long, code string, part int, gone int, row string, hash int"
    docs = spark.createDataFrame([(i, t, None if i == 1 else "en", None, None, "c", 1, 2, "r", None) for i, t in rows], schema)
    none = docs.where("doc_id > 99")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        left = stage(spark, docs, SMALL)
        assert left.columns == docs.columns and left.count() <= len(rows), name
        assert stage(spark, none, SMALL).count() == 0
    # Documents 1 and 2 are copies; 8 has two texts, one of them near the rows without an id.
    kept = corpus_pipeline.near_duplicates(spark, docs, SMALL).collect()
    assert sorted((r.doc_id is None, r.doc_id) for r in kept if r.text and len(r.text) > 100) == [(False, 1), (False, 7), (False, 8)]
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, SMALL)
    assert pieces.where("start = 0").count() == len(rows) and corpus_pipeline.STAGES[-1][1](spark, none, SMALL).count() == 0


def test_index_shapes():
    assert [simhash.index_shape(n, 4) for n in (0, 1_000, 10**6, 10**8, 3 * 10**10)] == [(5, 1), (5, 1), (5, 1), (6, 2), (7, 3)]
    assert all(b - 4 >= s for n in range(0, 60) for b, s in [simhash.index_shape(2**n, 4)])
