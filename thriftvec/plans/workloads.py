"""Experiment workloads on the given tables. Counts and ratios are the results; times are this machine's and reported apart.

No language model runs here: an answer is the retrieved passage's best-overlapping window, a stand-in for a generator.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import query
from ..functions.encoders import Encoder, encode
from ..functions.text import turns_to_objects
from ..operators import clusters as cl
from ..operators import graphs as g
from ..operators import measures as ms
from ..operators.baselines import smallest_ef
from ..operators.bm25 import bm25_build, bm25_bytes, bm25_search
from ..operators.exact import knn_exact
from ..operators.search import VectorIndex
from ..sources.storage import stored
from .inputs import bench_queries, objects, table
from .q_relational import LATENCY
from .q_search import bench_vectors, chunk_index, chunk_truth, disk_chunks, layered_chunks, ledgers, new_and_old, once

EF = (20, 40, 60, 100, 160)


def query_sets(spark, d) -> dict[str, DataFrame]:
    """Five sets of (query_id, text): items found verbatim in a document, other items, off-corpus strings (every part whose
    id is divisible by 20), two-hop pairs, and a twentieth of the chunks themselves, drawn by hash."""

    def make():
        b = bench_queries(spark, d)
        hit = table(spark, d, "documents").select(F.col("text").alias("doc")).join(F.broadcast(b), F.expr("contains(doc, text)"), "right").where("doc is not null").select("query_id").distinct()
        hit = stored(hit)
        nxt = b.select((F.col("query_id") - 1).alias("query_id"), F.col("text").alias("more"))
        part = table(spark, d, "part").where("p_partkey % 20 = 0").select(F.col("p_partkey").alias("query_id"), F.concat_ws(" ", "p_name", "p_type").alias("text"))
        mine = chunk_index(spark, d).objects.where("pmod(xxhash64(node_id), 20) = 0").select(F.col("node_id").alias("query_id"), "text")
        return {"verbatim": b.join(hit, "query_id", "left_semi"), "absent": b.join(hit, "query_id", "left_anti"), "off_corpus": part, "two_hop": b.join(nxt, "query_id").select("query_id", F.concat_ws(" ", "text", "more").alias("text")), "self": mine}

    return once(spark, ("sets", d), make)


def vectors_of(spark, d, name: str) -> DataFrame:
    return once(spark, ("qv", d, name), lambda: stored(encode(query_sets(spark, d)[name], Encoder("hash_unit", 256), "query_id").withColumnRenamed("v", "qv")))


def truth_of(spark, d, name: str, k: int = 3) -> DataFrame:
    def make():
        i = chunk_index(spark, d)
        v = once(spark, ("chunkvec", d), lambda: stored(encode(i.objects, i.encoder, "node_id")))
        return stored(knn_exact(v, vectors_of(spark, d, name), k))

    return once(spark, ("truthof", d, name, k), make)


def sweep(index: VectorIndex, q: DataFrame, truth: DataFrame, k: int, grid=EF, **spec) -> list[tuple[int, float, float, float, float]]:
    """(ef, mean recall, mean encodes, mean batches, seconds) over a grid of queue sizes."""
    out = []
    for ef in grid:
        t = time.perf_counter()
        f = index.search(q, k=k, ef=ef, **spec)
        s = f.stats.agg(F.avg("n_encoded"), F.avg("n_batches")).first()
        out.append((ef, ms.mean_recall(f.result, truth, k), float(s[0] or 0), float(s[1] or 0), time.perf_counter() - t))
    return out


def _frame(spark, rows, schema):
    return spark.createDataFrame([tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows], schema)


def _methods(spark, d):
    return {"recompute_all": {"mode": "recompute", "batch_target": None}, "interleaved": {"mode": "interleaved", "alpha": 0.3, "batch_target": None}, "batched": {"mode": "interleaved", "alpha": 0.3, "batch_target": 64}}


def methods(spark, d, q: DataFrame, texts: DataFrame, truth: DataFrame, target: float = 0.9, efs: tuple = (20, 40, 80, 160, 320, 640), probes: tuple = (1, 2, 4, 8, 16, 32)) -> dict:
    """Each method on its own index, with the smallest queue or number of probes that reaches the recall, all nodes or cells
    at last: name -> run() giving (effort or None, recall, result, objects encoded or read per query)."""
    i = chunk_index(spark, d)
    n = i.objects.count()
    cents, cells = once(spark, ("cents", d), lambda: _cells(spark, d))
    vec = once(spark, ("chunkvec", d), lambda: stored(encode(i.objects, i.encoder, "node_id")))
    lists = once(spark, ("lists", d), lambda: stored(vec.join(cells, "node_id").select("cell", "node_id", "v")))
    folder = once(spark, ("lists on disk", d), lambda: _on_disk(spark, lists))
    own = chunk_index(spark, d, k=18, prune=False, pq_ratio=35, ks=256)
    layered, disk = layered_chunks(spark, d), disk_chunks(spark, d)
    bm = once(spark, ("bm25", d), lambda: bm25_build(i.objects.select("node_id", "text")))

    def mean(counts: DataFrame, c: str) -> float:
        return float(counts.agg(F.avg(c)).first()[0] or 0)

    def by_ef(search, c):
        def run():
            ef, r, res, counts = smallest_ef(search, truth, 3, target, n, efs)
            return ef, r, res, mean(counts, c)

        return run

    def by_probes(search, c=None):
        def run():
            for p in (*probes, cents.count()):
                res, counts = search(p)
                res = stored(res)
                r = ms.mean_recall(res, truth, 3)
                if r >= target:
                    return p, r, res, mean(counts, c) if c else 0.0
            return None, r, res, mean(counts, c) if c else 0.0

        return run

    def found(f):
        return f.result, f.stats

    def plain():
        res = stored(bm25_search(bm, texts, 3))
        r = ms.mean_recall(res, truth, 3)
        return (1 if r >= target else None), r, res, 0.0

    return {
        "bm25": plain,
        "hnsw": by_ef(lambda ef: layered.search(q, k=3, ef=ef), "n_steps"),
        "ivf": by_probes(lambda p: (cl.ivf_search(lists, cents, q, 3, p), None)),
        "disk_graph": by_ef(lambda ef: disk.search(q, k=3, ef=ef), "n_reads"),
        "ivf_disk": by_probes(lambda p: (cl.ivf_search(spark.read.parquet(folder), cents, q, 3, p), None)),
        "ivf_recompute": by_probes(lambda p: cl.ivf_recompute_search(cells, cents, i.objects, i.encoder, q, 3, p), "n_recomputed"),
        "pq": by_ef(lambda ef: found(own.search(q, k=3, ef=ef, mode="pq")), "n_encoded"),
        "recompute": by_ef(lambda ef: found(i.search(q, k=3, ef=ef, alpha=0.3, batch_target=64)), "n_encoded"),
    }


def _on_disk(spark, lists: DataFrame) -> str:
    from ..sources.storage import shared_folder

    path = shared_folder(spark)
    cl.ivf_write(lists, path)
    return path


def _bytes(spark, d) -> dict[str, int]:
    """Measured bytes of each method's own index."""
    i = chunk_index(spark, d)
    size, own = i.storage(), chunk_index(spark, d, k=18, prune=False, pq_ratio=35, ks=256).storage()
    hnsw, disk = layered_chunks(spark, d).storage(), disk_chunks(spark, d).storage()
    cells = 4 * i.meta["dim"] * max(2, int(size["nodes"] ** 0.5))
    bm = once(spark, ("bm25", d), lambda: bm25_build(i.objects.select("node_id", "text")))
    return {"bm25": int(bm25_bytes(bm)), "hnsw": hnsw["graph"] + hnsw["vectors"], "ivf": cells + size["vectors"], "ivf_disk": cells + size["vectors"], "disk_graph": disk["sectors"] + disk["codes"], "ivf_recompute": cells + 4 * size["nodes"], "pq": own["padded"] + own["codes"], "recompute": size["csr"] + size["codes"]}


@query("w1_main_table")
def w1(spark, d):
    """One corpus, one question set: accuracy stand-in, bytes and search seconds of all methods, each on its own index with the
    least effort that reaches 0.9 recall@3 (effort null: not reached even with all nodes)."""
    q, truth, n = bench_vectors(spark, d), chunk_truth(spark, d), chunk_index(spark, d).objects.count()
    size, rows = _bytes(spark, d), []
    for name, run in methods(spark, d, q, bench_queries(spark, d), truth).items():
        t = time.perf_counter()
        effort, r, res, cost = run()
        sec = time.perf_counter() - t
        f1 = answers(spark, d, res).agg(F.avg("f1")).first()[0]
        rows.append((name, effort, r, float(f1 or 0), cost, size[name], size[name] / n, 100 * (1 - size[name] / size["hnsw"]), sec))
    return _frame(spark, rows, "method string, effort int, recall double, f1 double, cost double, bytes long, bytes_per_object double, saving_pct double, seconds_of_all_efforts double")


def answers(spark, d, result: DataFrame) -> DataFrame:
    """Extractive stand-in: over the retrieved passages, the window of the gold answer's length with the best overlap."""
    gold = bench_queries(spark, d)
    i = chunk_index(spark, d)
    j = result.join(i.objects.select("node_id", F.col("text").alias("passage")), "node_id").join(gold, "query_id")
    from ..functions.text import tokens

    n = F.greatest(F.size(tokens(F.col("text"))), F.lit(1))
    w = F.split("passage", " ")
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(w) - n + 1)))
    win = j.withColumn("n", n).withColumn("w", w).select("query_id", F.col("text").alias("gold"), "w", "n", at.alias("at")).select("query_id", "gold", F.array_join(F.slice("w", F.col("at"), F.col("n")), " ").alias("pred"))
    return ms.token_f1(win)


@query("w2_storage")
def w2(spark, d):
    """Bytes of all methods at this corpus' size and, by formula, at 60 million and at 79 billion objects."""
    i = chunk_index(spark, d)
    size, n, raw = i.storage(), i.objects.count(), i.objects.agg(F.sum(F.length("text"))).first()[0]
    deg, dim = size["edges"] / size["nodes"], i.meta["dim"]
    rows = []
    for scale, count, dims, cb in (("measured", n, dim, size["codes"] / n), ("60M", 6e7, 768, 30.72), ("100TB", 7.9e10, 768, 30.72)):
        base = sum(ms.storage_bytes("hnsw", count, dims))
        for m in ("hnsw", "hnsw_csr", "disk_graph", "ivf", "ivf_disk", "ivf_recompute", "pq", "bm25", "recompute"):
            meta, vec = ms.storage_bytes(m, count, dims, avg_degree=deg if scale == "measured" and m == "recompute" else 9 if m == "recompute" else 18, code_bytes=cb, cells=count**0.5, postings=(raw / n if scale == "measured" else 1270) * count * 0.78)
            rows.append((scale, m, float(meta), float(vec), float(100 * (1 - (meta + vec) / base))))
    return _frame(spark, rows, "scale string, method string, metadata double, vectors double, saving_pct double")


@query("w3_latency_sets")
def w3(spark, d):
    """Per question set and method: the least effort with recall@3 of 0.9, its cost in objects encoded, read or visited, and
    seconds of one search with it; effort null where not even all nodes or cells reach the recall."""
    rows = []
    gen = {"verbatim": 20.86, "off_corpus": 69.60, "absent": 17.17, "two_hop": 23.28, "self": 20.86}
    for name, texts in query_sets(spark, d).items():
        q, truth = vectors_of(spark, d, name), truth_of(spark, d, name)
        for m, run in methods(spark, d, q, texts, truth, efs=(20, 80, 320), probes=(2, 8, 32)).items():
            t = time.perf_counter()
            effort, r, _, cost = run()
            sec = time.perf_counter() - t
            rows.append((name, m, effort, r, cost if effort else None, sec, 100 * sec / (sec + gen[name])))
    return _frame(spark, rows, "query_set string, method string, effort int, recall double, cost double, seconds_of_all_efforts double, overhead_pct double")


def _cells(spark, d):
    i = chunk_index(spark, d)
    v = once(spark, ("chunkvec", d), lambda: stored(encode(i.objects, i.encoder, "node_id")))
    k = max(2, int(v.count() ** 0.5))
    c = stored(cl.to_float(cl.kmeans_fixed(v, k, 1)))
    return c, stored(cl.nearest_cells(v, c, 1).select("node_id", "cell"))


@query("w4_personal_sets")
def w4(spark, d):
    """Web pages, conversations and opaque vectors as corpora: encodes, recall and storage saved."""
    from ..functions.text import chunk, strip_html

    pages = chunk(table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), strip_html(F.col("html")).alias("text"))).select(F.col("chunk_id").alias("node_id"), "text")
    mail = turns_to_objects(table(spark, d, "conversations")).select((F.col("conv_id") * 1000 + F.col("turn")).alias("node_id"), "text")
    img = table(spark, d, "embeddings").select(F.col("vec_id").alias("node_id"), F.array_join(F.transform("embedding", lambda x: x.cast("string")), ",").alias("text"))
    rows = []
    for name, obj, enc in (("pages", pages, Encoder()), ("mail", mail, Encoder()), ("opaque", img, Encoder("lookup", 64))):
        obj = stored(obj.where("text is not null").dropDuplicates(["text"]))
        i = VectorIndex.build(obj, enc, k=9)
        v = stored(encode(obj, enc, "node_id"))
        q = stored(v.where("pmod(xxhash64(node_id), 20) = 0").select(F.col("node_id").alias("query_id"), F.col("v").alias("qv")))
        f = i.search(q, k=3, ef=60, alpha=0.3)
        size = i.storage()
        rows.append((name, size["nodes"], ms.mean_recall(f.result, knn_exact(v, q, 3), 3), float(f.stats.agg(F.avg("n_encoded")).first()[0]), 100 * (1 - (size["csr"] + size["codes"]) / (size["padded"] + size["vectors"]))))
    return _frame(spark, rows, "corpus string, objects long, recall double, encodes double, saving_pct double")


@query("w5_answers")
def w5(spark, d):
    """Exact match and F1 of the extractive stand-in by method, each at 0.9 recall@3 or, where that is not reached, with all
    its nodes."""
    out = None
    for name, run in methods(spark, d, bench_vectors(spark, d), bench_queries(spark, d), chunk_truth(spark, d)).items():
        a = answers(spark, d, run()[2]).agg(F.round(F.avg((F.col("f1") == 1).cast("int")), 6).alias("em"), F.round(F.avg("f1"), 6).alias("f1")).withColumn("method", F.lit(name))
        out = a if out is None else out.unionByName(a)
    return out


@query("w6_search_ablation")
def w6(spark, d):
    """Naive recomputation, interleaving, batching: encodes and batches at equal recall (0.9) by question set."""
    i = chunk_index(spark, d)
    rows = []
    for name in query_sets(spark, d):
        q, truth = vectors_of(spark, d, name), truth_of(spark, d, name)
        base = None
        for m, spec in _methods(spark, d).items():
            ok = next((x for x in sweep(i, q, truth, 3, **spec) if x[1] >= 0.9), None)
            base = base or (ok[2] if ok else None)
            rows.append((name, m, ok[0] if ok else None, ok[1] if ok else None, ok[2] if ok else None, ok[3] if ok else None, base / ok[2] if ok and base else None))
    return _frame(spark, rows, "query_set string, method string, ef int, recall double, encodes double, batches double, fewer_encodes double")


def pruned(spark, d) -> dict[str, DataFrame]:
    """The original graph and its prunings to about half the average degree."""

    def make():
        i = chunk_index(spark, d, k=18, prune=False)
        e = i.edges
        v = once(spark, ("chunkvec", d), lambda: stored(encode(i.objects, i.encoder, "node_id")))
        half = g.average_degree(e) / 2
        low, hub = g.calibrate(lambda m: stored(g.hub_prune(e, e, 60, max(1, m), 0.02)), 1, 30, half, 5, whole=True)
        cap, cut = g.calibrate(lambda m: stored(g.degree_cap(e, max(1, m), "rebuild", v)), 1, 40, half, 5, whole=True)
        return {"original": e, "hub": hub, "random": stored(g.random_prune(e, 0.5)), "cap": cut}

    return once(spark, ("pruned", d), make)


@query("w7_pruning_quality")
def w7(spark, d):
    """Objects to recompute for recall targets by pruning rule, at about equal average degree."""
    from dataclasses import replace

    i = chunk_index(spark, d, k=18, prune=False)
    q, truth = bench_vectors(spark, d), chunk_truth(spark, d)
    rows = []
    for name, e in pruned(spark, d).items():
        adj = stored(g.adjacency(e).select("node_id", "nbrs").withColumn("shard", F.lit(0)))
        s = sweep(replace(i, adjacency=adj, edges=e), q, truth, 3, mode="recompute", batch_target=None)
        for target in (0.85, 0.9, 0.94, 0.96):
            rows.append((name, g.average_degree(e), target, ms.at_recall([(x[1], x[2]) for x in s], target)))
    return _frame(spark, rows, "graph string, avg_degree double, target double, encodes double")


@query("w8_degrees")
def w8(spark, d):
    """Degrees of the four graphs and how often nodes of a degree class are visited."""
    out = None
    for name, e in pruned(spark, d).items():
        r = g.degrees(e).agg(F.lit(name).alias("graph"), F.count("*").alias("nodes"), F.sum("out_deg").alias("edges"), F.max("out_deg").alias("max_degree"), F.expr("percentile(out_deg, 0.5)").alias("median"), F.expr("percentile(out_deg, 0.98)").alias("p98"))
        out = r if out is None else out.unionByName(r)
    return out


@query("w9_updates")
def w9(spark, d):
    """Encodes of an insert by grade, counted by the encoder's meter, the saving against the naive one, and a buffered add, which
    encodes the object alone."""
    rows, base = [], None
    for mode, led in ledgers(spark, d)[0].items():
        r = led.agg(F.count("*"), F.avg("called")).first()
        base = base or r[1]
        rows.append((mode, r[0], float(r[1]), float(base / r[1])))
    i, new, _ = new_and_old(spark, d)
    rows.append(("buffered", encode(new, i.encoder, "node_id").count(), 1.0, float(base)))
    return _frame(spark, rows, "mode string, inserts long, encodes double, fewer double")


@query("w10_shards")
def w10(spark, d):
    """Sharded builds against one build: recall, and storage peak."""
    from ..operators.shards import assign_two, peak_storage

    i = chunk_index(spark, d)
    q, truth = bench_vectors(spark, d), chunk_truth(spark, d)
    v = once(spark, ("chunkvec", d), lambda: stored(encode(i.objects, i.encoder, "node_id")))
    rows = []
    for k in (1, 2, 4, 8):
        x = chunk_index(spark, d, shards=k) if k > 1 else i
        f = x.search(q, k=3, ef=60, mode="recompute", batch_target=None, executor="local")
        home = assign_two(v, x.centres) if k > 1 else v.select("node_id", F.lit(0).alias("cell"))
        p = peak_storage(stored(home), 256, 18).first()
        rows.append((k, ms.mean_recall(f.result, truth, 3), float(f.stats.agg(F.avg("n_encoded")).first()[0]), p["sharded_peak"] if k > 1 else p["single_peak"]))
    return _frame(spark, rows, "shards int, recall double, encodes double, peak_bytes long")


@query("w11_small_encoder")
def w11(spark, d):
    """A quarter-width encoder: recall against the wide encoder's truth, bytes read by the encoder."""
    q, truth = bench_queries(spark, d), chunk_truth(spark, d)
    rows = []
    for spec in ("hash_unit:256", "hash_small:256"):
        i = once(spark, ("enc", d, spec), lambda spec=spec: VectorIndex.build(stored(objects(spark, d)), spec, k=9))
        f = i.search(q, k=3, ef=60, alpha=0.3)
        rows.append((spec, i.meta["dim"], ms.mean_recall(f.result, truth, 3), float(f.stats.agg(F.avg("n_encoded")).first()[0])))
    return _frame(spark, rows, "encoder string, dim int, recall double, encodes double")


@query("w12_cache")
def w12(spark, d):
    """Vectors of hot objects kept: share kept, encodes, hit rate; results don't change."""
    i = chunk_index(spark, d)
    q = bench_vectors(spark, d)
    f = i.search(q, k=3, ef=60, alpha=0.3, return_trace=True)
    pop = stored(f.trace.groupBy("node_id").agg(F.count("*").alias("n")))
    full, n = i.storage()["vectors"], i.objects.count()
    base = float(f.stats.agg(F.avg("n_encoded")).first()[0])
    rows = [(0.0, base, 0.0)]
    for share in (2.5, 5.0, 10.0):
        c = i.with_cache(int(full * share / 100), pop)
        e = float(i.search(q, k=3, ef=60, alpha=0.3, cache=c).stats.agg(F.avg("n_encoded")).first()[0])
        rows.append((share, e, 1 - e / base))
    assert n
    return _frame(spark, rows, "cached_pct double, encodes double, hit_rate double")


@query("w13_breakdown")
def w13(spark, d):
    """Shares of cheap distances, exact distances and steps of an interleaved search."""
    i = chunk_index(spark, d)
    f = i.search(bench_vectors(spark, d), k=3, ef=60, alpha=0.3, return_trace=True)
    return f.trace.groupBy("query_id").agg(F.count("*").alias("steps"), F.sum("n_approx").alias("cheap"), F.sum("n_exact").alias("exact")).agg(F.round(F.avg("steps"), 3).alias("steps"), F.round(F.avg("cheap"), 3).alias("cheap"), F.round(F.avg("exact"), 3).alias("exact"), F.round(F.sum("exact") / F.sum("cheap"), 6).alias("share_encoded"))


@query("w14_data_lake")
def w14(spark, d):
    """One index per source: bytes saved by not storing vectors, and how many searches would outweigh them."""
    i = chunk_index(spark, d)
    o = i.objects.groupBy("source").agg(F.count("*").alias("objects"))
    saved = F.col("objects") * (4 * i.meta["dim"])
    return o.select("source", "objects", saved.alias("bytes_saved"), F.floor(F.col("objects") / 300).alias("searches_to_encode_all"))


@query("w15_popularity")
def w15(spark, d):
    """Rank-skewed replay of the questions: the cache of the hottest 5% of nodes is built from the first half of the replay and
    run on the second: encodes without and with it, and whether results agree."""
    i = chunk_index(spark, d)
    q, n = bench_vectors(spark, d), bench_vectors(spark, d).count()
    f = i.search(q, k=3, ef=60, alpha=0.3, return_trace=True)
    u = F.conv(F.substring(F.md5(F.col("event_id").cast("string")), 1, 8), 16, 10).cast("double") / (1 << 32)
    replay = table(spark, d, "events").select(F.floor(F.lit(n) * F.pow(u, 3)).alias("query_id"), (F.dayofmonth("ts") <= 15).alias("early"))
    times = stored(replay.groupBy("query_id", "early").agg(F.count("*").alias("times")))
    pop = f.trace.select("query_id", "node_id").join(times.where("early"), "query_id").groupBy("node_id").agg(F.sum("times").alias("n"))
    k = max(1, i.objects.count() // 20)
    c = stored(i.with_cache(4 * i.meta["dim"] * k, stored(pop)))
    with_cache = i.search(q, k=3, ef=60, alpha=0.3, cache=c)
    late = times.where("not early")
    cost = lambda s: float(s.join(late, "query_id").agg(F.sum(F.col("n_encoded") * F.col("times")) / F.sum("times")).first()[0])
    a, b = cost(f.stats), cost(with_cache.stats)
    same = f.result.select("query_id", "rank", "node_id").exceptAll(with_cache.result.select("query_id", "rank", "node_id")).count() == 0
    return _frame(spark, [(k, a, b, 1 - b / a, same)], "cached long, encodes double, encodes_cached double, hit_rate double, same_results boolean")


@query("w16_coorder_graph")
def w16(spark, d):
    """Structural rules on the parts that share orders: edges, packed and padded bytes."""
    e = stored(g.coorder_graph(table(spark, d, "lineitem")).withColumn("dist", -F.col("w").cast("double")))
    rows = []
    for name, x in (("original", e), ("hub", g.hub_prune(e, e, 200, 40, 0.02)), ("random", g.random_prune(e, 0.5)), ("cap", g.degree_cap(e, 60))):
        r = g.degrees(x).agg(F.count("*"), F.sum("out_deg"), F.max("out_deg")).first()
        rows.append((name, r[0], r[1], r[2], 4 * (r[1] + r[0] + 1), 4 * r[0] * 206))
    return _frame(spark, rows, "graph string, nodes long, edges long, max_degree long, csr_bytes long, padded_bytes long")


@query("batch_profile")
def batch_profile(spark, d):
    """Objects in encoder batches by batching target: calls and mean fill."""
    i = chunk_index(spark, d)
    out = None
    for target in (1, None, 16, 64):
        s = ms.batch_stats(i.search(bench_vectors(spark, d), k=3, ef=60, alpha=0.3, batch_target=target).stats).withColumn("target", F.lit(str(target)))
        out = s if out is None else out.unionByName(s)
    return out


@query("budget_fit")
def budget_fit(spark, d):
    """Caps for a space budget: of all settings within bytes and recall, the one with fewest encodes."""
    from dataclasses import replace

    i = chunk_index(spark, d, k=18, prune=False)
    q, truth = bench_vectors(spark, d), chunk_truth(spark, d)
    budget = 4 * i.edges.count() * 0.6
    rows = []
    for cap in (30, 60):
        for low in (6, 12, 18):
            e = stored(g.hub_prune(i.edges, i.edges, cap, low, 0.02))
            size = 4 * e.count()
            adj = stored(g.adjacency(e).select("node_id", "nbrs").withColumn("shard", F.lit(0)))
            s = sweep(replace(i, adjacency=adj, edges=e), q, truth, 3, (60,), mode="recompute", batch_target=None)[0]
            rows.append((cap, low, size, bool(size <= budget), s[1], s[2]))
    best = min((r for r in rows if r[3] and r[4] >= 0.85), key=lambda r: r[5], default=None)
    return _frame(spark, [(*r, r == best) for r in rows], "cap int, low int, bytes long, within boolean, recall double, encodes double, chosen boolean")


__all__ = ["LATENCY", "query_sets", "sweep"]
