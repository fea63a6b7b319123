"""Set-form operators, measures, storage formulas, persistence and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from thriftvec.functions.encoders import Encoder, encode
from thriftvec.functions.text import chunk
from thriftvec.operators import graphs as g
from thriftvec.operators import measures as ms
from thriftvec.operators import pq
from thriftvec.operators.exact import knn_exact
from thriftvec.operators.search import VectorIndex
from thriftvec.plans.inputs import objects


@pytest.fixture(scope="module")
def points(spark):
    r = np.random.default_rng(1)
    x = r.normal(size=(60, 8)).astype("float32")
    return spark.createDataFrame([(i, [float(v) for v in a]) for i, a in enumerate(x)], "node_id long, v array<float>")


def test_chunk_edges(spark):
    d = spark.createDataFrame([(1, None), (2, ""), (3, "a b c d e"), (4, "x")], "doc_id long, text string")
    assert [(r["doc_id"], r["pos"], r["text"]) for r in chunk(d, 2).orderBy("chunk_id").collect()] == [(3, 0, "a b"), (3, 1, "c d"), (3, 2, "e"), (4, 0, "x")]
    assert [r["text"] for r in chunk(d.where("doc_id = 3"), 3, 1).orderBy("chunk_id").collect()] == ["a b c", "c d e"]
    with pytest.raises(ValueError):
        chunk(d, 2, 2)


def test_exact_edges(spark, points):
    q = points.select(F.col("node_id").alias("query_id"), F.col("v").alias("qv")).where("query_id < 3")
    assert knn_exact(points, q, 100).count() == 180
    assert knn_exact(points, q, 0).count() == 0
    assert knn_exact(points, q.limit(0), 3).count() == 0
    assert knn_exact(points.limit(0), q, 3).count() == 0
    a = [tuple(r)[:3] for r in knn_exact(points, q, 5).orderBy("query_id", "rank").collect()]
    assert a == [tuple(r)[:3] for r in knn_exact(points, q, 5, plan="expr").orderBy("query_id", "rank").collect()]


def test_equal_distances_go_by_id(spark):
    b = spark.createDataFrame([(i, [1.0, 0.0]) for i in range(30, 0, -1)], "node_id long, v array<float>")
    q = spark.createDataFrame([(0, [0.0, 0.0])], "query_id long, qv array<float>")
    assert [r["node_id"] for r in knn_exact(b, q, 4).orderBy("rank").collect()] == [1, 2, 3, 4]


def test_pq_shape():
    assert pq.pq_shape(768, 100) == (32, 256) and pq.pq_shape(768, 35) == (96, 256)


def test_flat_pq_is_exact_when_every_subvector_is_a_codeword(spark, points):
    sub = pq.subvectors(points, 4, 8)
    book = pq.seeded(sub, points.select("node_id", F.col("node_id").cast("int").alias("code")))
    codes = pq.pq_encode(points, book)
    q = points.select(F.col("node_id").alias("query_id"), F.col("v").alias("qv")).where("query_id < 5")
    got = [tuple(r)[:3] for r in pq.pq_topk(codes, q, book, 5).orderBy("query_id", "rank").collect()]
    assert got == [tuple(r)[:3] for r in knn_exact(points, q, 5).orderBy("query_id", "rank").collect()]


def test_pruning_limits(spark, points):
    e = g.base_graph(points, 6).cache()
    assert g.random_prune(e, 1.0).count() == e.count() and g.random_prune(e, 0.0).count() == 0
    h = g.hub_prune(e, e, 10, 2, 0.05)
    assert h.groupBy("u").count().agg(F.max("count")).first()[0] <= 10
    assert g.hub_prune(e, e, 100, 100, 0.1).count() == e.count()
    assert g.hubs(e, 0.0).count() == 0 and g.hubs(e, 1.0).count() == 60
    assert {tuple(r) for r in g.from_csr(g.to_csr(e)).select("u", "v").collect()} == {tuple(r) for r in e.select("u", "v").collect()}


def test_measures(spark):
    t = spark.createDataFrame([(1, 1, 10), (1, 2, 11), (2, 1, 12), (2, 2, 13)], "query_id long, rank int, node_id long")
    r = spark.createDataFrame([(1, 1, 10), (1, 2, 99)], "query_id long, rank int, node_id long")
    assert {tuple(x) for x in ms.recall_at_k(r, t, 2).collect()} == {(1, 0.5), (2, 0.0)}
    p = spark.createDataFrame([(1, "The cat sat", "a cat sat"), (2, "x y", "y z"), (3, "", "")], "query_id long, pred string, gold string")
    assert {tuple(x) for x in ms.exact_match(p).collect()} == {(1, 1), (2, 0), (3, 1)}
    assert {tuple(x) for x in ms.token_f1(p).collect()} == {(1, 1.0), (2, 0.5), (3, 1.0)}
    assert ms.at_recall([(0.8, 5), (0.9, 9), (0.95, 12)], 0.9) == 9 and ms.at_recall([(0.5, 1)], 0.9) is None


def test_storage_against_published_gigabytes():
    n = 6e7
    for method, meta, vec, kw in (("hnsw", 15, 173, {}), ("recompute", 2, 2, {"avg_degree": 9}), ("pq", 15, 5, {"code_bytes": 88})):
        a, b = ms.storage_bytes(method, n, 768, **kw)
        assert a / 1e9 == pytest.approx(meta, rel=0.12) and b / 1e9 == pytest.approx(vec, rel=0.12)


@pytest.fixture(scope="module")
def index(spark, sf):
    from thriftvec.plans.inputs import objects
    from thriftvec.sources.storage import stored

    return VectorIndex.build(stored(objects(spark, sf)), "hash_unit:64", k=9)


def test_interleaving_needs_fewer_encodes(spark, sf, index):
    from thriftvec.plans.inputs import bench_queries

    q = bench_queries(spark, sf)
    truth = knn_exact(encode(index.objects, index.encoder, "node_id"), encode(q, index.encoder, "query_id").withColumnRenamed("v", "qv"), 3)
    out = {}
    for name, spec in {"all": {"mode": "recompute"}, "half": {"alpha": 0.5}, "tenth": {"alpha": 0.1}}.items():
        f = index.search(q, k=3, ef=60, batch_target=None, **spec)
        out[name] = (ms.mean_recall(f.result, truth, 3), f.stats.agg(F.avg("n_encoded")).first()[0])
    assert out["all"][1] > out["half"][1] > out["tenth"][1]
    assert out["all"][0] > 0.85 and out["all"][0] >= out["tenth"][0]


def test_frontier_equals_kernel(spark, sf, index):
    from thriftvec.plans.frontier import search
    from thriftvec.plans.inputs import bench_queries

    q = encode(bench_queries(spark, sf).where("query_id < 4"), index.encoder, "query_id").withColumnRenamed("v", "qv")
    a = search(index, q, k=3, ef=5, alpha=0.5)
    b = index.search(q, k=3, ef=5, alpha=0.5, batch_target=None)
    key = lambda f: sorted((r["query_id"], r["rank"], r["node_id"]) for r in f.result.collect())
    assert key(a) == key(b)
    assert {tuple(r) for r in a.stats.select("query_id", "n_exact").collect()} == {tuple(r) for r in b.stats.select("query_id", "n_exact").collect()}


def test_save_and_load(spark, sf, index, tmp_path):
    from thriftvec.plans.inputs import bench_queries
    from thriftvec.sources import index_io

    path = str(tmp_path / "index")
    index_io.save(index, path)
    again = index_io.load(spark, path, index.objects, Encoder("hash_unit", 64))
    q = bench_queries(spark, sf)
    key = lambda f: sorted(tuple(r)[:3] for r in f.result.collect())
    assert key(index.search(q, k=3, ef=30)) == key(again.search(q, k=3, ef=30))
    with pytest.raises(ValueError):
        index_io.load(spark, path, index.objects, Encoder("hash_unit", 128))
    index_io.register(spark)
    assert spark.read.format("thriftvec").option("table", "codes").load(path).count() == index.objects.count()


def test_stream_equals_batch(spark, sf, tmp_path):
    from thriftvec.plans.inputs import table
    from thriftvec.streaming.buffered import BufferedIndex, mutations

    enc = Encoder("hash_unit", 32)
    base = spark.createDataFrame([(1_000_000, [0.0] * 32)], "node_id long, v array<float>")
    ev = table(spark, sf, "events")
    src = str(tmp_path / "in")
    mutations(ev).repartition(3).write.parquet(src)
    one = BufferedIndex(spark, enc, base, str(tmp_path / "buf"))
    stream = spark.readStream.schema("op string, node_id long, text string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(src)
    one.add_stream(stream, str(tmp_path / "cp")).awaitTermination()
    rows = {r["node_id"] for r in one.buffer().collect()}
    assert rows == {r["node_id"] for r in mutations(ev).where("op = 'insert'").select("node_id").distinct().collect()}
    q = spark.createDataFrame([(1, [0.1] * 32)], "query_id long, qv array<float>")
    before = [tuple(r) for r in one.search(q, 5).collect()]
    one.drain()
    assert one.buffer().count() == 0 and [tuple(r) for r in one.search(q, 5).collect()] == before


def test_answer_windows(spark, monkeypatch):
    from types import SimpleNamespace

    from thriftvec.plans import workloads

    passage = " ".join(f"w{i}" for i in range(40))
    gold = [(i, " ".join(f"w{j}" for j in range(i, i + 10))) for i in range(31)] + [(31, passage + " more")]
    index = SimpleNamespace(objects=spark.createDataFrame([(1, passage)], "node_id long, text string"))
    monkeypatch.setattr(workloads, "bench_queries", lambda s, d: spark.createDataFrame(gold, "query_id long, text string"))
    monkeypatch.setattr(workloads, "chunk_index", lambda s, d: index)
    found = spark.createDataFrame([(i, 1) for i, _ in gold], "query_id long, node_id long")
    got = {r["query_id"]: r["f1"] for r in workloads.answers(spark, "", found).collect()}
    assert got == {**dict.fromkeys(range(31), 1.0), 31: round(80 / 81, 6)}


@pytest.mark.parametrize("name", ["knn_l2", "range_search", "ivf_search_all", "pq_adc_topk", "knn_sparse_docs"])
def test_pairs_are_no_rows(spark, sf, name):
    """Searches of many queries keep pairs inside tasks: no join of rows with queries, terms or look-up tables."""
    from thriftvec import catalog

    plan = catalog.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    scans = plan.split("MapInArrow")[0]
    assert "MapInArrow" in plan and "Join" not in scans


def test_copies_tie_in_every_block(spark):
    """Distances of equal vectors are equal wherever the rows lie, and large groups of copies go by id."""
    r = np.random.default_rng(7)
    x = r.normal(size=(1500, 16)).astype("float32")
    x[400:1400] = x[3]
    x[20, 0] = np.nan
    rows = [(i, [float(v) for v in x[i]]) for i in r.permutation(1500).tolist()] + [(9000, None)]
    base = spark.createDataFrame(rows, "node_id long, v array<float>").repartition(3)
    q = base.where("node_id in (3, 5, 700)").select(F.col("node_id").alias("query_id"), F.col("v").alias("qv"))
    for metric in ("l2", "cosine", "ip"):
        got, want = ([tuple(r) for r in knn_exact(base, q, 12, metric, plan=p).orderBy("query_id", "rank").collect()] for p in ("blocked", "expr"))
        want = [w for w in want if not np.isnan(w[3])]
        assert got == want
    assert [r["node_id"] for r in knn_exact(base, q.where("query_id = 3"), 4).orderBy("rank").collect()] == [3, 400, 401, 402]


def test_sparse_search_needs_a_shared_coordinate(spark):
    from thriftvec.operators.exact import knn_exact_sparse

    rows = spark.createDataFrame([(1, [1, 1, -2]), (2, [3]), (3, []), (4, [2, -2, -1]), (5, None)], "node_id long, at array<int>")
    q = spark.createDataFrame([(7, 0, 2), (7, 1, 1)], "query_id long, dim int, v long")
    assert [tuple(r) for r in knn_exact_sparse(rows, q, 5, 4).orderBy("rank").collect()] == [(7, 1, 1, -3), (7, 2, 4, 2)]


def test_formulas_read_given_tables(spark, sf):
    """Storage and overhead come from the tables, in Spark's tasks, and match their SQL."""
    import duckdb

    from thriftvec import catalog

    for name, t in (("storage_formula", "embeddings"), ("overhead_pct", "conversations")):
        got = catalog.queries()[name](spark, sf)
        assert any(f"{t}.parquet" in f for f in got.inputFiles())
        duck = duckdb.connect()
        duck.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
        want = duck.sql(catalog.oracle_sql()[name])
        assert sorted(map(tuple, got.select(*want.columns).collect())) == sorted(want.fetchall())


def test_chunks_cut_each_text_once(spark, sf):
    plan = lambda d: d._jdf.queryExecution().optimizedPlan().toString()
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source")
    assert plan(chunk(docs)).count("regexp_extract_all") == 1
    assert plan(objects(spark, sf)).count("regexp_extract_all") == 1
    c = chunk(docs).collect()
    first: dict = {}
    for r in sorted(c, key=lambda r: r["chunk_id"]):
        first.setdefault(r["text"], (r["chunk_id"], r["text"], r["lang"], r["source"]))
    assert sorted(map(tuple, objects(spark, sf).collect()), key=lambda r: r[0]) == sorted(first.values())


def test_lloyd_makes_no_rows_of_points_by_codewords(spark):
    """Whole-number rounds inside tasks equal the relational form; vectors without a distance go to the first codeword."""
    import numpy as np

    rng = np.random.default_rng(3)
    for scale in (10**6, 10**8):
        x = rng.integers(-scale, scale, (300, 4))
        rows = [(i, i % 2, v.tolist()) for i, v in enumerate(x)] + [(900, 0, [1, None, 3, 4]), (901, 1, None), (902, 1, [5, 6])]
        p = spark.createDataFrame(rows, "node_id long, sub int, x array<long>")
        b = spark.createDataFrame([(s, c, x[s + 2 * c].tolist()) for s in (0, 1) for c in range(7)], "sub int, code int, centroid array<long>")
        near = pq.assign(p, b, "long").drop("dist")
        want: dict = {(r["sub"], r["code"]): list(r["centroid"]) for r in b.collect()}
        members: dict = {}
        for r in near.join(p, ["node_id", "sub"]).where("x is not null").collect():
            members.setdefault((r["sub"], r["code"]), []).append(r["x"])
        for key, m in members.items():
            want[key] = [sum(v[i] or 0 for v in m if i < len(v)) // sum(i < len(v) for v in m) for i in range(4)]
        got = pq.lloyd_fixed(p, b, 1)
        assert {(r["sub"], r["code"]): list(r["centroid"]) for r in got.collect()} == want


def test_single_precision_scan_leaves_few_pairs_to_direct_distances(monkeypatch):
    import numpy as np

    from thriftvec.operators import exact

    x = np.random.default_rng(4).normal(size=(6000, 32))
    x[7] = x[8] + 1e-12
    ids, seen = np.arange(len(x)) * 2, []
    inner = exact.pairwise
    monkeypatch.setattr(exact, "pairwise", lambda m, x, c, q, r, *a: (seen.append(len(r)), inner(m, x, c, q, r, *a))[1])
    best = exact.Best(ids[:400], 9)
    exact.scan(best, x[:400], ids, x, "l2", True)
    assert sum(seen) < 400 * 30
    for i in (0, 7, 8, 399):
        d = exact.direct_distances("l2", x, x[i])
        d[i] = np.nan
        at = exact.nearest_rows(d, ids, 9)
        assert best.i[i].tolist() == ids[at].tolist() and best.d[i].tolist() == d[at].tolist()
    big = exact.Best(ids[:5], 2)
    exact.scan(big, x[:5] * 1e60, ids, x * 1e60, "l2")
    assert big.i[:, 0].tolist() == ids[:5].tolist()


def test_held_token_counts_are_metered(monkeypatch):
    """A text that comes again is not cut again; vectors and the meter are the same as without."""
    from thriftvec.functions import encoders

    texts = ["a b b c", "", None, "a b b c", "D e", "d E", "a b b c"]
    cut, inner = [], encoders.Encoder.units
    monkeypatch.setattr(encoders.Encoder, "units", lambda self, t: (cut.append(t), inner(self, t))[1])
    for kind in ("hash_unit", "hash_int", "hash_ngram", "hash_small"):
        plain, kept = Encoder(kind, 64), Encoder(kind, 64, held={})
        want = plain.encode(texts)
        cut.clear()
        assert np.array_equal(kept.encode(texts), want) and len(cut) == 4
        assert np.array_equal(kept.encode(texts), want) and len(cut) == 4
        assert (kept.meter.objects, kept.meter.bytes, kept.meter.calls) == (14, 2 * plain.meter.bytes, 2)


@pytest.mark.parametrize("name", ["hnsw_search", "disk_graph_search"])
def test_baselines_build_no_other_index(spark, sf, monkeypatch, name):
    """Their chunks, their graph and the true neighbours are made without the graph of the proposed index."""
    from thriftvec import catalog
    from thriftvec.operators.search import VectorIndex
    from thriftvec.plans import q_search

    monkeypatch.setattr(q_search, "_built", {})
    monkeypatch.setattr(VectorIndex, "build", lambda *a, **k: pytest.fail("built"))
    got = catalog.queries()[name](spark, sf).collect()
    assert len(got) == 40 and all(r["found"] == 3 and r["good"] for r in got)
