"""Set-similarity join of word n-grams by vertical partitioning.

The global order of n-grams (frequent ones last, then by hash) is cut into vertical fragments. The leading fragment
of a document is its prefix: two documents that are similar enough share an n-gram there, which gives the candidates.
A candidate pair's overlap is counted in each of the other cuts of the order separately and summed per pair.

Equal sets are one node. Of nodes that share many n-grams only the nearest partners are verified at first; verified
links merge nodes to components, and the next round looks at pairs between different components only, until a round
leaves no partner out. So a large group of copies costs a few links per document, and no link that matters is lost.

At 100 TB: per document about a tenth of its n-grams is shuffled; hot n-grams are dealt to chunk pairs of bounded size;
text is shuffled in the first round with a candidate of the document, and once only; only a bounded list of frequent n-grams is broadcast, and it
merely orders n-grams, whatever its size.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, stored
from .components import components
from .words import Words, blocks, mix, run_hash

FREQUENT = 1 << 17  # entries of the order's list of frequent n-grams
MASK_WORDS = 16  # 64-bit words of a node's parity mask
LARGE_WORDS = 64  # of the mask of sets that are too large for the small one to tell apart
WIDE_WORDS, WIDE_FROM = 128, 1500  # of the mask for a last look before verification, for sets of more n-grams than that
FRAGMENTS = 4
CHUNK = 512  # nodes of one n-gram that one task compares with another chunk
PARTNERS = 2  # candidates per node and n-gram in the first round, and per node over all its n-grams; 16 times as many in each further one


def _grams(w: Words, k: int) -> list[np.ndarray]:
    """Per row the sorted distinct hashes of its n-grams; fewer than k words: the whole sequence as one."""
    h = run_hash(w.hash, k)
    out = []
    for r in range(w.rows):
        s, n = w.bounds[r], w.counts[r]
        if n >= k:
            out.append(np.unique(h[s : s + n - k + 1]))
        elif n:
            out.append(mix(run_hash(w.hash[s : s + n], int(n)) + np.uint64(n)))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def _frequent(k: int, least: int):
    schema = pa.schema([("gram", pa.int64()), ("c", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text", 4 << 20):
            g = _grams(Words(b.column("text"), lower=True), k)
            u, c = np.unique(np.concatenate(g), return_counts=True) if g else (np.empty(0, np.uint64), np.empty(0, int))
            keep = c >= least
            yield pa.RecordBatch.from_arrays([pa.array(u[keep].view(np.int64)), pa.array(c[keep].astype(np.int64))], schema=schema)

    return run


def _signature(u: np.ndarray) -> int:
    return int(mix(np.array([np.add.reduce(mix(u ^ np.uint64(0xA5A5A5A5))) + np.uint64(len(u))], np.uint64)).view(np.int64)[0])


def _parity(u: np.ndarray, words: int) -> bytes:
    """Parities of hash buckets: two sets differ in at least as many n-grams as their parities in bits."""
    return np.packbits((np.bincount((u >> np.uint64(7)).astype(np.int64) % (words * 64), minlength=words * 64) & 1).astype(np.uint8)).tobytes()


def _wide(percent: int):
    """(a, b, na, nb, x, y) -> (a, b) of pairs that the wide masks don't rule out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint64).reshape(-1, WIDE_WORDS) for c in ("x", "y"))
            d = np.bitwise_count(x ^ y).sum(1, dtype=np.int64)
            n = b.column("na").to_numpy() + b.column("nb").to_numpy()
            yield b.select(["a", "b"]).filter(pa.array(d * (100 + percent) <= n * (100 - percent)))

    return run


def _nodes(k: int, percent: int, order):
    schema = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("node", pa.int64()), ("mask", pa.binary()), ("prefix", pa.list_(pa.int64())), ("wide", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top, rank = order.value
        # parities of unlike sets differ in half the bits; beyond this size that is less than the limit allows
        many = 0.6 * MASK_WORDS * 64 * (100 + percent) / (4 * max(1, 100 - percent))
        for b in blocks(batches, "text"):
            sets = _grams(Words(b.column("text"), lower=True), k)
            ns, nodes, masks, prefixes, wide = [], [], [], [], []
            for u in sets:
                n = len(u)
                ns.append(n)
                nodes.append(_signature(u) if n else None)
                masks.append(_parity(u, LARGE_WORDS if n > many else MASK_WORDS))
                wide.append(_parity(u, WIDE_WORDS) if n > WIDE_FROM else None)
                length = n - (percent * n + 99) // 100 + 1 if n else 0
                if len(top) and n > length:
                    at = np.searchsorted(top, u)
                    at[at == len(top)] = 0
                    late = np.where(top[at] == u, rank[at], 0)
                    prefixes.append(u[np.argsort(late, kind="stable")[:length]].view(np.int64))
                else:
                    prefixes.append(u[:length].view(np.int64))
            off = np.cumsum([0, *map(len, prefixes)])
            flat = np.concatenate([np.empty(0, np.int64), *prefixes])
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(ns, pa.int64()), pa.array(nodes, pa.int64()), pa.array(masks, pa.binary()), pa.ListArray.from_arrays(pa.array(off, pa.int32()), pa.array(flat)), pa.array(wide, pa.binary())], schema=schema)

    return run


def _partners(percent: int, most: int):
    """Rows sorted by (gram, i, j) -> candidate pairs of different components with the bits that their masks differ in; a
    row with a gram only says that nodes of that n-gram had further partners."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("gram", pa.int64()), ("bits", pa.int64())])

    def pairs(t: dict[str, np.ndarray], left: np.ndarray, right: np.ndarray, same: bool) -> tuple:
        n, comp, node, mask, large = t["n"], t["comp"], t["node"], t["mask"], t["large"]
        ln, rn = n[left][:, None], n[right][None, :]
        ok = (comp[left][:, None] != comp[right][None, :]) & (100 * np.minimum(ln, rn) >= percent * np.maximum(ln, rn))
        if same:
            ok &= np.triu(np.ones(ok.shape, bool), 1)
        x, y = np.nonzero(ok)
        a, b = [], []
        dist = []
        for s in range(0, len(x), 1 << 17):
            p, q = left[x[s : s + (1 << 17)]], right[y[s : s + (1 << 17)]]
            d = np.bitwise_count(mask[p] ^ mask[q]).sum(1, dtype=np.int64)
            big = np.flatnonzero((large[p] >= 0) & (large[q] >= 0))
            if len(big):
                d[big] = np.bitwise_count(t["larges"][large[p[big]]] ^ t["larges"][large[q[big]]]).sum(1, dtype=np.int64)
            keep = d * (100 + percent) <= (n[p] + n[q]) * (100 - percent)
            a.append(p[keep])
            b.append(q[keep])
            dist.append(d[keep])
        if not a:
            return ()
        a, b, dist = map(np.concatenate, (a, b, dist))
        o = np.lexsort((b, dist, a))
        a, b, dist = a[o], b[o], dist[o]
        start = np.flatnonzero(np.r_[True, a[1:] != a[:-1]])[: len(a)]
        place = np.arange(len(a)) - np.repeat(start, np.diff(np.r_[start, len(a)]))
        keep = place < most
        more = not keep.all()
        a, b = a[keep], b[keep]
        return np.minimum(node[a], node[b]), np.maximum(node[a], node[b]), dist[keep], more

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None

        def groups(tab: pa.Table):
            g = np.stack([tab.column(c).to_numpy() for c in ("gram", "i", "j")])
            cut = np.flatnonzero(np.r_[True, (g[:, 1:] != g[:, :-1]).any(0)])
            t = {c: tab.column(c).to_numpy() for c in ("node", "n", "comp", "side")}
            raw = tab.column("mask").to_pylist()
            is_large = np.array([len(x) > MASK_WORDS * 8 for x in raw], bool)
            larges = np.frombuffer(b"".join([x for x, z in zip(raw, is_large, strict=True) if z]), np.uint64).reshape(-1, LARGE_WORDS)
            t["large"] = np.where(is_large, np.cumsum(is_large) - 1, -1)
            t["mask"] = np.zeros((len(raw), MASK_WORDS), np.uint64)
            t["mask"][~is_large] = np.frombuffer(b"".join([x for x, z in zip(raw, is_large, strict=True) if not z]), np.uint64).reshape(-1, MASK_WORDS)
            # a large mask folds to a small one
            t["mask"][is_large] = np.bitwise_xor.reduce(larges.reshape(-1, LARGE_WORDS // MASK_WORDS, MASK_WORDS), 1)
            for s, e in zip(cut, np.r_[cut[1:], tab.num_rows], strict=True):
                if e - s > 1:
                    part = {c: v[s:e] for c, v in t.items()} | {"larges": larges}
                    if part["comp"].min() == part["comp"].max():
                        continue
                    same = bool(g[1, s] == g[2, s])
                    all_rows = np.arange(e - s)
                    left, right = (all_rows, all_rows) if same else (all_rows[part["side"] == 0], all_rows[part["side"] == 1])
                    if got := pairs(part, left, right, same):
                        yield *got[:3], g[0, s], got[3]

        def emit(tab):
            got = list(groups(tab))
            if got:
                more = sorted({int(x[3]) for x in got if x[4]})
                a, b, bits = (np.concatenate([x[i] for x in got]) for i in (0, 1, 2))
                gram = np.concatenate([np.repeat(np.array([x[3] for x in got], np.int64), [len(x[0]) for x in got]), np.array(more, np.int64)])
                pad = pa.nulls(len(more), pa.int64())
                yield pa.RecordBatch.from_arrays([*(pa.concat_arrays([pa.array(c), pad]) for c in (a, b)), pa.array(gram), pa.concat_arrays([pa.array(bits), pad])], schema=schema)

        for b in batches:
            tab = pa.Table.from_batches([b]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([b])])
            last = [tab.column(c)[-1].as_py() for c in ("gram", "i", "j")] if tab.num_rows else None
            if last is None:
                continue
            differ = np.zeros(tab.num_rows, bool)
            for c, v in zip(("gram", "i", "j"), last, strict=True):
                differ |= tab.column(c).to_numpy() != v
            end = int(np.flatnonzero(differ)[-1]) + 1 if differ.any() else 0
            if end:
                yield from emit(tab.slice(0, end))
            rest = tab.slice(end)
        if rest is not None and rest.num_rows:
            yield from emit(rest)

    return run


def _segments(k: int):
    schema = pa.schema([("node", pa.int64()), ("part", pa.int32()), ("seg", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges = np.array([(i << 64) // FRAGMENTS for i in range(1, FRAGMENTS)], np.uint64)
        for b in blocks(batches, "text"):
            out: tuple[list, list, list] = ([], [], [])
            for u, want in zip(_grams(Words(b.column("text"), lower=True), k), b.column("node").to_pylist(), strict=True):
                if len(u) and _signature(u) == want:
                    for i, seg in enumerate(np.split(u, np.searchsorted(u, edges))):
                        out[0].append(want)
                        out[1].append(i)
                        out[2].append(seg.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema, strict=True)], schema=schema)

    return run


def _overlaps():
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("part", pa.int32()), ("c", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c = [len(np.intersect1d(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), assume_unique=True)) for x, y in zip(b.column("x").to_pylist(), b.column("y").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b"), b.column("part"), pa.array(c, pa.int64())], schema=schema)

    return run


def _merged(comp: DataFrame | None, links: DataFrame) -> DataFrame:
    """comp(node, component), further links(a, b) -> comp. Only components that the links reach are contracted again."""
    if comp is None:
        return components(links)
    for c in ("a", "b"):
        own = comp.select(F.col("node").alias(c), F.col("component").alias("_c"))
        links = links.join(own, c, "left").withColumn(c, F.coalesce("_c", c)).drop("_c")
    up = stored(components(links))
    moved = comp.join(up.select(F.col("node").alias("component"), F.col("component").alias("up")), "component", "left").select("node", F.coalesce("up", "component").alias("component"))
    return moved.unionByName(up.join(comp, "node", "left_anti").select("node", "component"))


def similar_groups(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs(doc_id, text) -> one row per input row: doc_id, n_shingles, component_id.

    Texts are lower-cased for A-Z and cut into words at ASCII white space; a document's set is its distinct k-word
    shingles, or its whole word sequence where it has fewer words. Two documents link when the intersection makes up
    at least `percent` per cent of the union; component_id is the smallest doc_id reachable by links. Documents
    without words (null, empty, blank) have n_shingles 0 and stand alone; rows without doc_id have no component.
    Repeated rows are links of equal sets. N-grams are compared by 64-bit hashes.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    count = docs.mapInArrow(_frequent(k, 3), "gram long, c long").groupBy("gram").agg(F.sum("c").alias("c")).where("c >= 8")
    top = count.orderBy(F.desc("c"), "gram").limit(FREQUENT).toArrow()
    gram, c = top.column("gram").to_numpy().view(np.uint64), top.column("c").to_numpy()
    o = np.argsort(gram)
    order = spark.sparkContext.broadcast((gram[o], c[o]))

    known = stored(docs.mapInArrow(_nodes(k, percent, order), "doc_id long, n long, node long, mask binary, prefix array<long>, wide binary"))
    first = known.where("node is not null and doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("doc_id"))
    one = stored(known.join(first, ["node", "doc_id"]).dropDuplicates(["node"]))
    tokens = one.select("node", F.explode("prefix").alias("gram"))
    often = tokens.groupBy("gram").agg(F.count("*").alias("c")).where("c > 1")
    tokens = stored(tokens.join(often, "gram").select("gram", "node", F.ceil(F.col("c") / CHUNK).cast("int").alias("k")))
    facts = stored(one.select("node", "n", "mask"))
    large = stored(one.where(F.col("wide").isNotNull()).select("node", "n", "wide"))
    reps = stored(one.select("node", "doc_id"))
    sets = stored(known.select("doc_id", "n", "node"))
    discard(one, known)  # the prefixes in them are the bulk

    comp: DataFrame | None = None
    segs: DataFrame | None = None
    parts: list[DataFrame] = []
    tried: DataFrame | None = None
    most = PARTNERS
    while True:
        r = tokens.join(facts, "node")
        r = r.withColumn("comp", F.col("node")) if comp is None else r.join(comp, "node", "left").withColumn("comp", F.coalesce("component", "node"))
        mixed = r.groupBy("gram").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("gram") if comp is not None else None
        r = r if mixed is None else r.join(mixed, "gram", "left_semi")
        mine = F.pmod(F.xxhash64("node"), F.col("k")).cast("int")
        r = r.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
        r = r.select("gram", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "node", "n", "comp", "mask", (F.col("mine") > F.col("other")).cast("int").alias("side"))
        r = r.repartition("gram", "i", "j").sortWithinPartitions("gram", "i", "j")
        found = stored(r.mapInArrow(_partners(percent, most), "a long, b long, gram long, bits long"))
        cand = found.where("a is not null").groupBy("a", "b").agg(F.min("bits").alias("bits"), F.min("gram").alias("gram"))
        # of the partners that a node meets by all its n-grams the nearest go first: mostly they join a group of near copies
        place = [F.row_number().over(Window.partitionBy(x).orderBy("bits", y)) for x, y in (("a", "b"), ("b", "a"))]
        ranked = stored(cand.withColumn("first", F.least(*place) <= most))
        cand = ranked.where("first").select("a", "b")
        # n-grams whose nodes had more partners than the limit come again, the others are done
        again = stored(found.where("a is null").select("gram").unionByName(ranked.where("not first").select("gram")).distinct())
        more = again.limit(1).count()
        if tried is not None:
            cand = cand.join(tried, ["a", "b"], "left_anti")
        both = cand.select("a", "b").join(large.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("wide").alias("x")), "a", "left")
        both = both.join(large.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("wide").alias("y")), "b", "left")
        short = both.where("x is null or y is null").select("a", "b")
        cand = stored(short.unionByName(both.where("x is not null and y is not null").mapInArrow(_wide(percent), "a long, b long")))
        tried = cand.select("a", "b") if tried is None else tried.unionByName(cand.select("a", "b"))
        # nodes come up in any round: partners beyond the limit, or pairs that the wide masks ruled out before
        wanted = cand.select(F.explode(F.array("a", "b")).alias("node")).distinct()
        if segs is not None:
            wanted = wanted.join(segs.select("node").distinct(), "node", "left_anti")
        wanted = wanted.join(reps, "node")
        if segs is None:
            segs = stored(docs.join(wanted, "doc_id").mapInArrow(_segments(k), "node long, part int, seg binary"))
            parts.append(segs)
        else:
            wanted = stored(wanted)
            if wanted.limit(1).count():
                parts.append(stored(docs.join(wanted, "doc_id").mapInArrow(_segments(k), "node long, part int, seg binary")))
                segs = segs.unionByName(parts[-1])
        pair = cand.select("a", "b").join(segs.select(F.col("node").alias("a"), "part", F.col("seg").alias("x")), "a")
        pair = pair.join(segs.select(F.col("node").alias("b"), "part", F.col("seg").alias("y")), ["b", "part"]).select("a", "b", "part", "x", "y")
        both = pair.mapInArrow(_overlaps(), "a long, b long, part int, c long").groupBy("a", "b", "part").agg(F.max("c").alias("c")).groupBy("a", "b").agg(F.sum("c").alias("c"))
        size = facts.select("node", "n")
        good = both.join(size.select(F.col("node").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("node").alias("b"), F.col("n").alias("nb")), "b")
        good = good.where(F.lit(100) * F.col("c") >= F.lit(percent) * (F.col("na") + F.col("nb") - F.col("c"))).select("a", "b")
        old, comp = comp, stored(_merged(comp, stored(good)))
        discard(old, found, ranked)
        if not more:
            break
        most *= 16
        new = stored(tokens.join(again, "gram", "left_semi"))
        discard(tokens, again)
        tokens = new
    discard(tokens, facts, large, *parts)
    owner = sets.where("doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("d"))
    least = owner.join(comp, "node", "left").withColumn("component", F.coalesce("component", "node"))
    low = least.groupBy("component").agg(F.min("d").alias("low"))
    named = least.join(low, "component").select("node", "low")
    out = sets.join(named, "node", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce(F.when(F.col("n") > 0, F.col("low")), F.col("doc_id"))).alias("component_id"))
