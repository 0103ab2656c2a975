import numpy as np
import pytest
import xxhash

from tests.conftest import MIDDLE, SMALL
from vecquant.operators import codec, relational
from vecquant.operators.fit import Search
from vecquant.plans import workloads
from vecquant.sources import features, stores
from vecquant.streaming import encode


def test_store_round_trip(spark, tmp_path):
    base = spark.read.parquet(f"{SMALL}/embeddings.parquet").where("vec_id < 20").select("vec_id", "embedding")
    s = Search(curve="pwl", m=2, fixed_iter=3)
    meta = stores.Meta(d=64, m=2, bits=8, curve="pwl", shards=2)
    for _ in range(2):  # written again, the rows are the same
        stores.write_store(codec.encode(base, s), str(tmp_path / "s"), meta)
    rows, read = stores.read_store(spark, str(tmp_path / "s"))
    assert read == meta and rows.count() == 20
    assert codec.decode(rows, read.search(), 64).count() == 20


def test_readers(spark, tmp_path):
    (tmp_path / "v.txt").write_text("1 0.5 1.5\n2 -1 2\n")
    rows = {r.vec_id: r.embedding for r in stores.read_vectors(spark, str(tmp_path / "v.txt"), "text").collect()}
    assert rows == {1: [0.5, 1.5], 2: [-1.0, 2.0]}
    (tmp_path / "v.csv").write_text("vec_id,line\n7,1 2\n")
    assert stores.read_vectors(spark, str(tmp_path / "v.csv"), "csv").first().embedding == [1.0, 2.0]
    (tmp_path / "v.json").write_text('{"vec_id": 3, "embedding": [1, 2.5]}\n')
    assert stores.read_vectors(spark, str(tmp_path / "v.json"), "json").first().embedding == [1.0, 2.5]
    x = np.arange(6, dtype="<f4").reshape(3, 2)
    raw = b"".join(np.array([2], "<i4").tobytes() + r.tobytes() for r in x)
    (tmp_path / "v.fvecs").write_bytes(raw)
    rows = stores.read_fvecs(spark, str(tmp_path / "v.fvecs")).orderBy("vec_id").collect()
    assert [r.embedding for r in rows] == x.tolist() and [r.vec_id for r in rows] == [0, 1, 2]
    (tmp_path / "e.fvecs").write_bytes(b"")
    assert stores.read_fvecs(spark, str(tmp_path / "e.fvecs")).count() == 0


def test_text_vectors(spark):
    df = spark.createDataFrame([(1, "a b a"), (2, ""), (3, None), (4, "A  B a")], "doc_id long, text string")
    rows = {r.vec_id: np.array(r.embedding) for r in features.text_vectors(df, 32).collect()}
    assert set(rows) == {1, 4} and np.allclose(rows[1], rows[4]) and abs(np.linalg.norm(rows[1]) - 1) < 1e-6


def test_group_arrays(spark):
    assert workloads.event_arrays(spark, MIDDLE).count() > 50
    assert workloads.supplier_arrays(spark, SMALL).first().embedding.__len__() == 512


def test_joins(spark):
    a = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (1, "2024-01-01 02:00:00"), (2, "2024-01-01 00:00:00")], "k int, t string").selectExpr("k", "cast(t as timestamp) ts")
    b = spark.createDataFrame([(1, "2024-01-01 01:00:00", "x"), (1, "2024-01-01 00:00:00", "w")], "k int, t string, v string").selectExpr("k", "cast(t as timestamp) ts", "v")
    found = sorted((r.k, r.ts.hour, r.v) for r in relational.as_of(a, b, "ts", ["v"], ["k"]).collect())
    assert found == [(1, 0, "w"), (1, 2, "x"), (2, 0, None)]
    assert relational.interval(a, b, 3600, "k").count() == 3


def test_streams(spark, tmp_path):
    assert workloads.stream_equals_batch(spark, SMALL).first().differences == 0
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "e"))
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "e"))
    job = encode.running_mean(source, "event_type", "value", 1e9).writeStream.outputMode("update").format("memory").queryName("means").trigger(availableNow=True).start()
    job.awaitTermination()
    last = {r.event_type: (r.n, r.mean) for r in spark.sql("select event_type, max_by(n, n) n, max_by(mean, n) mean from means group by 1").collect()}
    for r in events.groupBy("event_type").agg({"value": "avg", "*": "count"}).collect():
        assert last[r.event_type][0] == r["count(1)"] and abs(last[r.event_type][1] - r["avg(value)"]) < 1e-6
    job = encode.dedup(source.unionByName(source), "event_id", late="400 days").writeStream.format("memory").queryName("once").trigger(availableNow=True).start()
    job.awaitTermination()
    assert spark.table("once").count() == events.count()


def test_sql_functions(spark):
    from vecquant.functions import sqlfn

    sqlfn.register(spark)
    sqlfn.register_views(spark, {"e": spark.read.parquet(f"{SMALL}/embeddings.parquet").where("vec_id < 5")})
    assert len(spark.sql("select vec_avg(embedding) m from e").first().m) == 64
    assert spark.sql("select t.* from e, lateral pcq_trace(embedding, 'logi', 8, 1) t where vec_id = 1").count() >= 10
    codes = spark.sql("select pcq_codes(embedding, 'unif', 4, 0D, 0D) c from e").first().c
    assert min(codes) == 0 and max(codes) == 15


def test_wide_gains_take_all_documents(spark, monkeypatch):
    seen = []

    def fits(base, bits, **kw):
        seen.append({r.vec_id for r in base.select("vec_id").collect()})
        return base.selectExpr("vec_id", "'logi' curve", "1.0D gain", "1 iters")

    monkeypatch.setattr(workloads, "fits", fits)
    workloads.wide_gains(spark, SMALL, d=16)
    docs = {r.doc_id for r in spark.read.parquet(f"{SMALL}/documents.parquet").where("trim(text) <> ''").collect()}
    assert seen == [docs, docs]


def test_text_fits_settle_with_all_curves(spark, monkeypatch):
    seen = []

    def fits(base, bits, names=("kuma", "logi", "pwl"), s=Search(), **kw):
        seen.append((set(names), s.max_iter))
        return base.selectExpr("vec_id", "'logi' curve", "1.0D gain", "1 iters")

    monkeypatch.setattr(workloads, "fits", fits)
    monkeypatch.setattr(workloads.measures, "gain_summary", lambda found, key: found)
    workloads.text_gains(spark, SMALL, 16)
    assert seen == [({"kuma", "logi", "pwl"}, Search().max_iter)]


def test_sample_by_hash_matches_the_library(spark):
    from vecquant.operators import prep

    kept = {r.vec_id for r in prep.sample(spark.range(2_000).withColumnRenamed("id", "vec_id"), 0.2, 3).collect()}

    def bucket(i):
        seed = xxhash.xxh64_intdigest((3).to_bytes(4, "little"), 42)
        h = xxhash.xxh64_intdigest(i.to_bytes(8, "little"), seed)
        return (h - 2**64 if h >= 2**63 else h) % 1_000_000

    assert kept == {i for i in range(2_000) if bucket(i) < 200_000}


def test_as_of_over_spans(spark):
    rng = np.random.default_rng(0)
    base = np.datetime64("2024-01-01T00:00:00")
    left = [(int(k), (base + np.timedelta64(int(t), "s")).item(), i) for i, (k, t) in enumerate(zip(rng.integers(0, 3, 200), rng.integers(0, 500_000, 200), strict=True))]
    right = [(int(k), (base + np.timedelta64(int(t), "s")).item(), i) for i, (k, t) in enumerate(zip(rng.integers(0, 2, 40), rng.permutation(500_000)[:40], strict=True))]
    a, b = spark.createDataFrame(left, "k int, ts timestamp, i int"), spark.createDataFrame(right, "k int, ts timestamp, v int")
    truth = {i: max(((t2, v) for k2, t2, v in right if k2 == k and t2 <= t), default=(None, None))[1] for k, t, i in left}
    for seconds in (60, 86_400, 10**9):
        assert {r.i: r.v for r in relational.as_of(a, b, "ts", ["v"], ["k"], seconds).collect()} == truth


def test_late_rows_however_arrivals_lie(spark):
    rng = np.random.default_rng(1)
    times = rng.integers(0, 100_000, 400)
    orders = np.cumsum(rng.choice([1, 10**9], 400))
    rows = [(int(o), (np.datetime64("2024-01-01T00:00:00") + np.timedelta64(int(t), "s")).item(), i) for i, (o, t) in enumerate(zip(orders, times, strict=True))]
    df = spark.createDataFrame(rows, "o long, ts timestamp, i int").repartition(4)
    latest = np.maximum.accumulate(times)
    late = {i for i in range(1, 400) if latest[i - 1] - times[i] > 3600}
    for ranges in (1, 8, 512):
        assert {r.i for r in encode.late_rows(df, 3600, "o", ranges=ranges).collect()} == late


def test_merging_adds_only_new_ids(spark, tmp_path):
    merge = encode.merge_batch(spark, str(tmp_path / "t"), shards=4)
    for number, ids in enumerate(((1, 2, 3), (2, 3, 4), (1, 2, 3), (), (90, 1))):
        merge(spark.createDataFrame([(i, f"b{number}") for i in ids], "vec_id long, v string"), number)
    found = {r.vec_id: r.v for r in spark.read.parquet(str(tmp_path / "t")).collect()}
    assert found == {1: "b0", 2: "b0", 3: "b0", 4: "b1", 90: "b4"}


def test_scratch_is_released(spark):
    path = workloads.scratch(spark, "gone")
    spark.range(3).write.parquet(path)
    assert spark.read.parquet(path).count() == 3 and workloads.release(spark) > 0
    assert workloads.release(spark) == 0


def test_queries_are_counted_before_they_are_gathered(spark, monkeypatch):
    from vecquant.operators import search

    queries = spark.createDataFrame([(1, [1.0, 2.0]), (2, [0.0, 1.0])], "query_id long, qvec array<double>")
    assert search.query_values(queries) == 4 and search.collect_queries(queries, 4)[1].shape == (2, 2)
    with pytest.raises(ValueError, match="too many"):
        search.collect_queries(queries, 3)


def test_token_vectors_are_those_of_seeded_generators():
    words = ["a", "é", "word", "x" * 99]
    one = [np.random.Generator(np.random.SFC64(xxhash.xxh64_intdigest(w.encode(), 3))).standard_normal(48, dtype=np.float32) for w in words]
    assert (features.token_vectors(words, 48, 3) == np.stack(one)).all() and features.token_vectors([], 48, 3).shape == (0, 48)
    keys = [0, 1, 2**32 - 1, 2**32, 2**64 - 1]
    assert features.seeded_states(np.array(keys, dtype=np.uint64)).tolist() == [np.random.SFC64(k).state["state"]["state"].tolist() for k in keys]


def test_text_vectors_are_made_once(spark):
    assert "MapInArrow" not in workloads.vector_set(spark, SMALL, 16)._jdf.queryExecution().executedPlan().toString()


def test_a_merged_batch_is_made_once(spark, tmp_path):
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for batch in batches:
            seen.add(batch.num_rows)
            yield batch

    merge = encode.merge_batch(spark, str(tmp_path / "t"), shards=2)
    merge(spark.range(10).withColumnRenamed("id", "vec_id").mapInArrow(count, "vec_id long"), 0)
    assert seen.value == 10 and spark.read.parquet(str(tmp_path / "t")).count() == 10


def test_inventory_makes_no_text_vectors(spark, monkeypatch):
    monkeypatch.setattr(workloads, "text_set", None)
    rows = {r.set: r.n for r in workloads.inventory(spark, SMALL).collect()}
    blank = spark.createDataFrame([(1, "  "), (2, None), (3, ""), (4, " x")], "doc_id long, text string")
    assert rows["text_768"] == rows["text_1536"] > 0 and [r.vec_id for r in features.worded(blank).collect()] == [4]
