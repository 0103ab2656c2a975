import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.conftest import MIDDLE, SMALL
from vecquant.operators import codec, graph, ivf, measures, pq, prep, search
from vecquant.operators.fit import Search
from vecquant.plans import cost, workloads


@pytest.fixture(scope="module")
def sides(spark):
    df = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").select("vec_id", "embedding")
    return search.holdout(df)


def brute(base, queries, k):
    b, qs = base.collect(), queries.collect()
    ids, x = np.array([r.vec_id for r in b]), np.array([r.embedding for r in b], dtype=float)
    out = {}
    for r in qs:
        s = x @ np.array(r.qvec, dtype=float)
        out[r.query_id] = ids[np.lexsort((ids, -s))[:k]].tolist()
    return out


def ranked(df):
    out = {}
    for r in sorted(df.collect(), key=lambda r: (r.query_id, r.rank)):
        out.setdefault(r.query_id, []).append(r.vec_id)
    return out


def test_exact_matches_brute_force(sides):
    assert ranked(search.exact_topk(*sides, 10)) == brute(*sides, 10)


def test_more_asked_than_there_are(sides):
    base, queries = sides
    assert all(len(v) == 9 for v in ranked(search.exact_topk(base.where("vec_id < 10"), queries, 50)).values())


def test_coded_search_and_recall(sides):
    base, queries = sides
    s = Search(bits=8, m=2, fixed_iter=10)
    mean = prep.fit_mean(base)
    found = search.coded_topk(codec.encode(base, s, mean), queries, s, 64, 10, mean=mean)
    truth = search.exact_topk(base, queries, 10)
    assert measures.recall_at_k(found, truth, 10).agg({"recall": "avg"}).first()[0] > 0.97
    assert measures.map_at_k(truth, truth, 10).agg({"average_precision": "avg"}).first()[0] == pytest.approx(1)


def test_graph_and_lists_reach_their_recall(sides):
    base, queries = sides
    truth = search.exact_topk(base, queries, 10)
    index = graph.build(base, shards=4, degree=32, window=64)
    assert measures.recall_at_k(graph.search(index, queries, 10, 80), truth, 10).agg({"recall": "avg"}).first()[0] > 0.9
    assert graph.degrees(index).agg({"most": "max"}).first()[0] <= 32
    centers = ivf.centroids(base, 8)
    found = ivf.search(ivf.assign(base, centers, 2), queries, centers, 10, 8)
    assert ranked(found) == ranked(truth)


def test_product_quantization(sides):
    base, queries = sides
    book = pq.train(base, 4, 64, 4)
    assert book.shape == (16, 64, 4)
    scanned = ranked(pq.scan_topk(pq.encode(base, book), book, queries, 10))
    decoded = ranked(search.exact_topk(pq.decode(pq.encode(base, book), book), queries, 10))
    same = np.mean([len(set(scanned[k]) & set(decoded[k])) / 10 for k in scanned])
    assert same > 0.99


def test_models():
    assert [round(cost.index_bytes(d, 8, 2)[2], 2) for d in (768, 1024, 1536)] == [3.05, 3.23, 3.44]
    assert [cost.payload_bytes(1024, 8, m) - 1024 for m in (2, 4, 8)] == [32, 64, 128]
    assert round(cost.set_gib(10_000_000, 1536), 1) == 57.2 and cost.block_layout(1024)[2] and not cost.block_layout(768)[2]
    assert cost.aligned_bytes(1024, 8, 2) == (1088, 0) and cost.aligned_bytes(1000, 8, 1) == (1024, 16)
    total = {(c, side): [n for _, s, _, n in cost.op_counts(c, 1) if s == side] for c in cost.OPERATIONS for side in ("encode", "decode")}
    assert total["pwl", "encode"] == [0, 0, 2, 0, 1] and total["kuma", "decode"] == [2, 2, 18, 8, 0]


def test_copies_count_as_the_rows_they_equal(spark):
    base = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5]), (2, [0.5, 0.5]), (3, [0.4, 0.0])], "vec_id long, embedding array<double>")
    queries = spark.createDataFrame([(9, [1.0, 0.5])], "query_id long, qvec array<double>")
    truth = search.exact_topk(base, queries, 2)
    # Codes put the copy with the larger id before the other: nothing is lost by that.
    coded = base.where("vec_id <> 2").unionByName(spark.createDataFrame([(2, [0.5, 0.501])], base.schema))
    candidates = search.exact_topk(base, queries, 4)
    found = {(r.store, r.r): r.recall for r in search.rerank_sweep(candidates, {"fp32": (base, None), "coded": (coded, None)}, queries, truth, 2, [1, 2]).collect()}
    assert found == {("fp32", 1.0): 1.0, ("fp32", 2.0): 1.0, ("coded", 1.0): 1.0, ("coded", 2.0): 1.0}


def test_measured_pairs_change_no_graph():
    x = np.random.default_rng(3).standard_normal((150, 12))
    held, graph._PAIRED = graph._PAIRED, 0
    try:
        plain = graph.build_rows(x, 16, 40)
    finally:
        graph._PAIRED = held
    made = graph.build_rows(x, 16, 40)
    assert (made[0] == plain[0]).all() and made[1] == plain[1]


def test_codebooks_are_trained_without_exploding_values(spark):
    df = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").select("vec_id", "embedding")
    rows = sorted(df.collect(), key=lambda r: r.vec_id)
    x = np.array([r.embedding for r in rows], dtype=float)
    book = pq.train(df.repartition(3), 4, 16, 3)
    assert all(np.array_equal(book[g], pq.lloyd(x[:, 4 * g : 4 * g + 4], 16, 3, g)) for g in range(16))


def test_round_trips_are_what_each_operator_finds(spark):
    base, queries = search.holdout(spark.read.parquet(f"{SMALL}/embeddings.parquet").where("vec_id < 60").select("vec_id", "embedding"))
    mean, found = prep.fit_mean(base), {}
    searches = [Search(bits=4, m=m, fixed_iter=4) for m in (1, 4)]
    trips = measures.round_trips(base.repartition(3, "vec_id"), queries, searches, mean, 5).cache()
    assert "Exchange" not in measures.round_trips(base.coalesce(1), queries, searches, mean, 5)._jdf.queryExecution().executedPlan().toString()
    key = lambda r: (r.query_id, r.rank, r.vec_id)
    ranked = search.rank_rows(trips.where("vec_id IS NOT NULL").select("m", "query_id", "vec_id", "score"), 5, "m")
    for m in (0, 1, 4):
        found[m] = sorted(key(r) for r in ranked.where(F.col("m") == m).collect())
    assert found[0] == sorted(key(r) for r in search.exact_topk(base, queries, 5).collect())
    for s in searches:
        coded = codec.encode(base, s, mean)
        assert found[s.m] == sorted(key(r) for r in search.coded_topk(coded, queries, s, 64, 5, mean=mean).collect())
        pairs = measures.pairs_of(base, codec.decode(coded, s, 64, mean))
        own = trips.where(F.col("m") == s.m).groupBy("query_id").agg(F.sum("error").alias("error")).where("error IS NOT NULL")
        apart = {r.query_id: r.error for r in measures.dot_error(pairs, queries).collect()}
        assert {r.query_id: pytest.approx(r.error) for r in own.collect()} == apart
        n, gain, recon = trips.where(F.col("m") == s.m).agg(F.sum("n"), F.sum("gain") / F.sum("n"), F.sum("recon") / F.sum("n")).first()
        assert n == base.count() and gain == pytest.approx(coded.agg(F.avg("gain")).first()[0])
        assert recon == pytest.approx(measures.mean_recon(pairs).first()[0])


def test_sub_vectors_join_no_vectors(spark, monkeypatch):
    monkeypatch.setattr(measures, "pairs_of", lambda *a: pytest.fail("vectors joined"))
    rows = {r.m: r for r in workloads.subvectors(spark, SMALL, 4, ms=(1, 8)).collect()}
    assert set(rows) == {1, 8} and all(0.5 < r.map <= 1 and r.gain > 1 for r in rows.values())
    assert rows[8].mean_recon < rows[1].mean_recon and rows[8].dot_error < rows[1].dot_error


def test_the_recall_query_searches_one_graph_of_many_rows(spark, monkeypatch):
    from vecquant.plans import catalog

    made, kept = [], workloads.kept
    monkeypatch.setattr(workloads, "kept", lambda df, *name: made.append(kept(df, *name)) or made[-1])
    # The given vectors and as many read backwards: more base rows than a shard of 500 would hold.
    rows = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").select("vec_id", "embedding")
    more = rows.select((F.col("vec_id") + 1_000_000).alias("vec_id"), F.reverse("embedding").alias("embedding"))
    monkeypatch.setattr(catalog, "_queries_of", lambda s, sf: search.holdout(rows.unionByName(more)))
    found = {r.window: r.recall for r in catalog.QUERIES["graph_recall"](spark, MIDDLE).collect()}
    (index,) = [df for df in made if "neighbors" in df.columns]
    assert index.count() == 900 and index.select("shard").distinct().count() == 1
    assert sorted(found) == [10, 20, 50, 100, 200] and found[10] <= found[200] and found[200] > 0.9


def test_a_graph_over_product_codes_is_that_of_their_vectors(sides):
    base, queries = sides
    book = pq.train(base, 4, 64, 2)
    codes = pq.encode(base, book)
    made, plain = graph.build(codes, shards=3, degree=16, window=40, book=book), graph.build(pq.decode(codes, book), shards=3, degree=16, window=40)
    assert "pq" in made.columns and "embedding" not in made.columns
    of = lambda df: {r.vec_id: (r.shard, list(r.neighbors), r.entry) for r in df.select("shard", "vec_id", "neighbors", "entry").collect()}
    assert of(made) == of(plain)
    assert ranked(graph.search(made, queries, 10, 60, book)) == ranked(graph.search(plain, queries, 10, 60))


def test_a_sweep_moves_a_fetched_vector_once(sides):
    base, queries = sides
    truth = search.exact_topk(base, queries, 10)
    candidates = search.exact_topk(base, queries, 50).withColumn("rank", F.lit(51) - F.col("rank"))
    scored = search.rerank_scores(candidates, base, queries, 10, 5)
    plan = scored._jdf.queryExecution().optimizedPlan().toString()
    assert "qvec" not in plan and scored.count() == 2500
    exact = {(r.query_id, r.vec_id): r.score for r in search.exact_topk(base, queries, 50).collect()}
    assert all(abs(r.score - exact[r.query_id, r.vec_id]) < 1e-9 for r in scored.collect())
    ranks = {(r.query_id, r.vec_id): r["rank"] for r in candidates.collect()}
    assert all(ranks[r.query_id, r.vec_id] == r.first_rank for r in scored.collect())
    found = {r.r: r.recall for r in search.rerank_sweep(candidates, {"fp32": (base, None)}, queries, truth, 10, [1, 4, 5]).collect()}
    assert found == {5.0: 1.0}
