"""Pipeline operators against brute force on small tables with nulls, ties, repeated rows and clashing columns."""

import hashlib
import itertools
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(t, lower=False):
    t = t or ""
    return WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t) if lower else t)


@pytest.fixture(scope="module")
def rows():
    r = random.Random(5)
    vocab = [f"w{i}" for i in range(400)]
    passage = " ".join(r.choice(vocab) for _ in range(70))
    docs = []
    for i in range(60):
        t = " ".join(r.choice(vocab) for _ in range(r.randint(1, 160)))
        docs.append((i, f"{t} {passage} end" if i % 7 == 0 else t, "en", "a" if i % 3 else None))
    base = docs[1][1]
    for i in range(60, 70):
        w = base.split()
        w[i % len(w)] = "changed"
        docs.append((i, " ".join(w), None, "b"))
    docs += [(70, None, "en", "b"), (71, "", "en", "b"), (72, " \t\n", None, "c"), (73, docs[0][1], "en", "a"), (74, docs[0][1], "en", "a"), (75, "one", "en", "c"), (76, "One", "en", "c"), (77, "x" * 5000 + " É 日本 " * 40, "fr", "c")]
    docs.append(docs[3])
    return docs


@pytest.fixture(scope="module")
def docs(spark, rows):
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    return d.withColumn("size", F.lit("clash")).withColumn("copy", F.lit(1)).withColumn("n_chars", F.length("text").cast("long"))


def test_words_and_runs():
    import pyarrow as pa

    from thriftvec.llm.words import Words, run_hash

    texts = ["", None, "a b  c", "\n\tfoo bar", "foo", "bar foo bar", "é x\x0by", "foo bar baz foo bar baz"]
    w = Words(pa.array(texts))
    assert list(w.counts) == [len(words(t)) for t in texts]
    flat = [x for t in texts for x in words(t)]
    assert len({(x, h) for x, h in zip(flat, w.hash)}) == len(set(flat)) == len(set(w.hash.tolist()))
    assert len(set(run_hash(w.hash, 3).tolist())) == len({tuple(flat[i : i + 3]) for i in range(len(flat) - 2)})


def test_components(spark):
    from thriftvec.llm.components import components

    r = random.Random(2)
    links = [(r.randint(0, 80), r.randint(0, 80)) for _ in range(60)] + [(i, i + 1) for i in range(200, 240)] + [(300, i) for i in range(301, 350)] + [(None, 4), (5, 5)]
    got = {x["node"]: x["component"] for x in components(spark.createDataFrame(links, "a long, b long")).collect()}
    p = {}

    def find(x):
        while p.setdefault(x, x) != x:
            x = p[x]
        return x

    for a, b in links:
        if a is not None and b is not None:
            a, b = find(a), find(b)
            p[max(a, b)] = min(a, b)
    assert got == {x: find(x) for x in p}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_substring(docs, rows):
    from thriftvec.llm.substring import remove_repeats

    first = {}
    for i, t, *_ in sorted(rows, key=lambda x: x[0]):
        w = words(t)
        for a in range(len(w) - 49):
            first.setdefault(tuple(w[a : a + 50]), i)
    got = {r["doc_id"]: r for r in remove_repeats(docs, digest=True).collect()}
    plain = {r["doc_id"]: r for r in remove_repeats(docs).collect()}
    assert remove_repeats(docs).count() == len(rows) and "size" in remove_repeats(docs).columns
    for i, t, *_ in rows:
        w = words(t)
        hit = [False] * len(w)
        for a in range(len(w) - 49):
            if first[tuple(w[a : a + 50])] < i:
                hit[a : a + 50] = [True] * 50
        kept = " ".join(x for x, h in zip(w, hit) if not h)
        g = got[i]
        assert (g["_n_words"], g["_n_removed"], g["_kept_sha256"]) == (len(w), sum(hit), hashlib.sha256(kept.encode()).hexdigest())
        assert plain[i]["_kept"] == (kept if any(hit) else t)
    assert remove_repeats(docs.limit(0)).count() == 0


@pytest.mark.parametrize("k,percent", [(3, 90), (5, 80)])
def test_jaccard(docs, rows, k, percent):
    from thriftvec.llm.jaccard import similar_groups

    sets = {}
    for i, t, *_ in rows:
        w = words(t, True)
        sets[i] = {tuple(w[a : a + k]) for a in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    p = {i: i for i in sets}

    def find(x):
        while p[x] != x:
            x = p[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            p[max(x, y)] = min(x, y)
    got = [tuple(r) for r in similar_groups(docs, k, percent).collect()]
    assert sorted(got) == sorted((i, len(sets[i]), find(i)) for i, *_ in rows)
    assert similar_groups(docs.limit(0), k, percent).count() == 0


@pytest.mark.parametrize("copies", [8, 700])
def test_jaccard_star(spark, copies):
    """Copies that link to the original, but not to each other: all beyond the first partners come in later rounds."""
    from thriftvec.llm.jaccard import CHUNK, similar_groups

    r = random.Random(copies)
    base = [f"s{i}" for i in range(602)]
    texts = [" ".join(base)]
    for i in range(copies):
        w = list(base)
        for p in r.sample(range(1, 200), 12):
            w[3 * p] = f"edit{i}-{p}"
        texts.append(" ".join(w))
    sets = [{tuple(w[a : a + 3]) for a in range(len(w) - 2)} for w in (t.split() for t in texts)]
    like = lambda a, b: 100 * len(a & b) >= 85 * len(a | b)
    assert all(like(sets[0], s) for s in sets) and not any(like(a, b) for a, b in itertools.combinations(sets[1:60], 2))
    # the original's place among the rows of an n-gram goes by hash: several small stars make sure that partners are cut
    rows = [(g * 1000 + i, " ".join(f"{g}x{w}" for w in t.split())) for g in range(4 if copies < CHUNK else 1) for i, t in enumerate(texts)]
    got = similar_groups(spark.createDataFrame(rows, "doc_id long, text string"), 3, 85).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in got) == [(i, i // 1000 * 1000) for i, _ in rows]


def test_span_encoder_is_exact():
    from tokenizers import Tokenizer

    from thriftvec.llm.tokens import SpanEncoder, default_path

    r = random.Random(1)
    odd = ["<|endoftext|> foo", "a  b\n c\n\n\nd  ", "I'm we'll 's x's", "x²3 Ⅷ İı", " .a", "\n", "\tfoo\x1cbar\x85q\xa0z", "é é 日本 　x", ""]
    odd += ["".join(r.choice("ab É.\n\n  1_,'\t²é́-<|>") for _ in range(r.randint(1, 14))) for _ in range(1500)]
    for name in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        e, t = SpanEncoder(default_path(name)), Tokenizer.from_file(default_path(name))
        for a in range(0, len(odd), 100):
            for x, ids in zip(odd[a : a + 100], e.encode(odd[a : a + 100])):
                assert ids == np.array(t.encode(x, add_special_tokens=False).ids, "<u4").tobytes(), (name, x)
        assert e.encode([None]) == [b""]


def test_packing(docs, rows):
    from tokenizers import Tokenizer

    from thriftvec.llm.packing import best_fit_decreasing, lower_bound, pack_documents
    from thriftvec.llm.tokens import default_path

    t = Tokenizer.from_file(default_path("word_bpe_49k.json"))
    got = [r.asDict() for r in pack_documents(docs, capacity=128, with_ids=True).collect()]
    by = Counter()
    for i, x, *_ in rows:
        ids = t.encode(x or "", add_special_tokens=False).ids + [0]
        for p, a in enumerate(range(0, len(ids), 128)):
            by[i, p, a, len(ids[a : a + 128]), zlib.crc32(np.array(ids[a : a + 128], "<u4").tobytes())] += 1
    assert Counter((g["doc_id"], g["piece"], g["start"], g["length"], g["ids_crc32"]) for g in got) == by
    seq = {}
    for g in got:
        seq.setdefault(g["sequence_id"], []).append((g["offset"], g["length"]))
    for s in seq.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        assert at <= 128
    n = np.array([g["length"] for g in got])
    assert lower_bound(n, 128) <= len(seq) <= best_fit_decreasing(n, 128)[0].max() + 2
    assert pack_documents(docs.limit(0)).count() == 0


def test_lower_bound_holds():
    from thriftvec.llm.packing import best_fit_decreasing, lower_bound

    assert lower_bound(np.array([60] * 5), 100) == 5 and lower_bound(np.array([34] * 6), 100) == 3
    r = np.random.default_rng(0)
    for _ in range(50):
        n = r.integers(1, 101, r.integers(1, 80))
        bins, off = best_fit_decreasing(n, 100)
        assert lower_bound(n, 100) <= bins.max() + 1 and np.bincount(bins, weights=n).max() <= 100
        assert (off + n <= 100).all()


def test_token_files(docs, rows, tmp_path):
    from tokenizers import Tokenizer

    from thriftvec.llm.token_codec import read_tokens, write_tokens
    from thriftvec.llm.tokens import default_path

    t = Tokenizer.from_file(default_path("byte_bpe_50k.json"))
    folder = str(tmp_path / "ids")
    write_tokens(docs, folder)
    got = sorted((r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"], bytes(r["ids"])) for r in read_tokens(docs.sparkSession, folder, True).collect())
    at, want = 0, []
    for i, x, *_ in sorted(rows, key=lambda r: r[0]):
        raw = np.array(t.encode(x or "", add_special_tokens=False).ids + [0], "<u4").tobytes()
        want.append((i, at, len(raw) // 4, zlib.crc32(raw), raw))
        at += len(raw) // 4
    assert got == sorted(want)
    write_tokens(docs.limit(0), str(tmp_path / "none"))
    assert read_tokens(docs.sparkSession, str(tmp_path / "none")).count() == 0


def test_huffman():
    from thriftvec.llm.token_codec import canonical, code_lengths, decode_table, pack_bits, unpack_bits

    fib = [1, 1]
    while len(fib) < 40:
        fib.append(fib[-1] + fib[-2])
    n = code_lengths(dict(enumerate(fib)))
    assert max(n.values()) <= 16 and sum(2.0**-x for x in n.values()) <= 1
    assert code_lengths({7: 3}) == {7: 1} and code_lengths({}) == {}
    free = code_lengths({0: 5, 1: 9, 2: 12, 3: 13, 4: 16, 5: 45})
    assert sorted(free.values()) == [1, 3, 3, 3, 4, 4]
    ids = np.random.default_rng(1).choice(40, 5000, p=np.array(fib) / sum(fib)).astype(np.uint32)
    p, marks = pack_bits(ids, *canonical(n))
    assert (unpack_bits([(p, marks, len(ids))], decode_table(n))[0] == ids).all()


def test_mixing(docs, rows):
    from thriftvec.llm.mixing import mix_sources, targets

    got = [r.asDict() for r in mix_sources(docs).collect()]
    assert len(got) == len(rows)
    size = Counter()
    for _, t, _, s in rows:
        size[s] += len(words(t))
    want = targets(dict(size))
    order = sorted(size, key=lambda s: (s is None, s or ""))
    assert [len(order), sum(want.values())] == [4, pytest.approx(sum(size.values()))]
    assert all(want[s] <= 3 * size[s] + 1e-6 for s in want)
    for s in order:
        mine = [g for g in got if g["source"] == s]
        assert all(g["taken"] <= 3 * g["size"] and g["target"] == pytest.approx(want[s]) and g["source_size"] == size[s] for g in mine)
        assert abs(sum(g["taken"] for g in mine) - want[s]) <= max(g["size"] for g in mine)
    again = [r.asDict() for r in mix_sources(docs.repartition(7)).collect()]
    key = lambda rs: sorted((g["doc_id"], g["taken"]) for g in rs)
    assert key(got) == key(again)
    assert mix_sources(docs.limit(0)).count() == 0


def test_flight_balances():
    from thriftvec.llm.mixing import flight

    r = np.random.default_rng(3)
    size, p = r.integers(1, 500, 400), np.full(400, 0.3)
    v = flight(p, size, np.random.default_rng(1), False)
    assert ((v > 0) & (v < 1)).sum() <= 2
    assert v.sum() == pytest.approx(p.sum()) and (v * size).sum() == pytest.approx((p * size).sum())
    v = flight(p, size, np.random.default_rng(1), True)
    assert set(np.unique(v)) <= {0.0, 1.0} and abs((v * size).sum() - (p * size).sum()) < 20


def test_embeddings(spark):
    from thriftvec.llm.embeddings import near_duplicates

    r = np.random.default_rng(5)
    x = r.normal(size=(300, 16))
    for i in range(0, 120, 3):
        x[i + 1], x[i + 2] = x[i] + r.normal(size=16) * 0.35, x[i]
    rows = [(i, [float(v) for v in a]) for i, a in enumerate(x)]
    bad = [(400, None), (401, [0.0] * 16), (402, [float("nan")] * 16), (403, [1.0] * 3), (404, [None] + [1.0] * 15), (None, [1.0] * 16)]
    got = {g["vec_id"]: g for g in near_duplicates(spark.createDataFrame(rows + bad, "vec_id long, embedding array<double>")).collect()}
    n = np.sqrt((x * x).sum(1))
    link = (x @ x.T) / np.outer(n, n) >= 0.9
    link |= (x[:, None] == x[None]).all(2)
    np.fill_diagonal(link, False)
    comp = np.arange(300)
    for _ in range(300):
        new = np.array([min([comp[i], *comp[link[i]]]) for i in range(300)])
        if (new == comp).all():
            break
        comp = new
    for i in range(300):
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (link[i].sum(), comp[i], comp[i] == i)
    for i, _ in bad[:-1]:
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True)
    assert got[None]["component_id"] is None
    assert near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_lm(docs, rows):
    from thriftvec.llm.lm_score import score_texts

    toks = {i: [*words(t, True), ""] for i, t, *_ in rows}
    texts = {i: t for i, t, *_ in rows}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i in toks}
    c = Counter(x for i, t, *_ in rows if not held[i] for x in [*words(t, True), ""])
    n, v = sum(c.values()), len(c)
    got = [r.asDict() for r in score_texts(docs).collect()]
    assert len(got) == len(rows)
    for g in got:
        t = toks[g["doc_id"]]
        assert (g["held_out"], g["n_tokens"], g["n_known"], g["train_tokens"]) == (held[g["doc_id"]], len(t), sum(c[x] > 0 for x in t), n)
        assert g["base_score"] == pytest.approx(sum(math.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in t))
        assert math.isfinite(g["score"]) and g["score"] < 0
        size = len((texts[g["doc_id"]] or "").encode())
        assert g["bits_per_byte"] == (pytest.approx(-g["score"] / math.log10(2) / size) if size else None)
    assert score_texts(docs.limit(0)).count() == 0


def test_lm_beats_the_base(spark):
    """Held-out texts of two made-up languages with phrases that recur: the model is better in all and on most."""
    from thriftvec.llm.lm_score import score_texts

    r = random.Random(3)
    vocab = [[f"{a}{b}{x}" for a in "bdgk" for b in "aeiou" for x in range(9)], [f"{a}{b}{x}" for a in "lmnr" for b in "aeiou" for x in range(9)]]
    phrases = [[" ".join(r.choice(v) for _ in range(8)) for _ in range(20)] for v in vocab]
    data = []
    for i in range(400):
        g = i % 2
        data.append((i, " ".join(r.choice(phrases[g]) if r.random() < 0.1 else r.choice(vocab[g]) for _ in range(r.randint(20, 120)))))
    got = [x.asDict() for x in score_texts(spark.createDataFrame(data, "doc_id long, text string")).where("held_out").collect()]
    assert len(got) > 50 and sum(g["score"] > g["base_score"] for g in got) > 0.9 * len(got)
    assert sum(g["score"] for g in got) > 0.9 * sum(g["base_score"] for g in got)


def _small_model(phrase=False):
    import pyarrow as pa

    from thriftvec.llm.lm_score import HITS, SPELLED, Model, Phrases, Tokens, Tree

    t = Tokens(pa.array(["a b c"]))
    tree = Tree(t.hash, np.array([50, 20, 9, 5]), 4)
    r = np.random.default_rng(1)
    phrases = Phrases.empty(1 << 10)
    if phrase:  # "a" at the beginning of a text
        one, two, word = t.contexts()
        slot = int(two[0] >> np.uint64(54))
        phrases.check[slot], phrases.follows[slot], phrases.seen[slot] = two[0] & np.uint64(0xFFFF), word[0], 3
    slots = 1 << 8
    return t.hash, Model(tree, phrases, r.integers(0, 9, 4 * slots + SPELLED + 2 * HITS).astype(np.uint32), slots)


@pytest.mark.parametrize("phrase", [False, True])
def test_lm_is_a_distribution(phrase):
    from types import SimpleNamespace

    from thriftvec.llm.lm_score import Tokens, mix

    known, m = _small_model(phrase)
    each = []
    for h in [*known, np.uint64(12345)]:
        t = SimpleNamespace(hash=np.array([h]), text=np.zeros(1, int), back=np.zeros(1, int), n=np.ones(1, int))
        t.contexts = lambda t=t: Tokens.contexts(t)
        d = m.decide(t)
        each.append(float(np.exp(mix(d, m.inputs(), m.hints(d), m.weights)[0])))
    if phrase:  # a foretold word is never coded by the tree: its share there is lost
        assert 0.5 < sum(each) <= 1 + 1e-5 and each[0] > 0
    else:
        assert sum(each) == pytest.approx(1, abs=1e-5)


def test_spelling_is_a_distribution():
    _, m = _small_model()
    for prefix in (b"", b"a", b"ab", b"abcdef"):
        at = len(prefix)
        p, start = m.bytes_odds([prefix + bytes([x]) for x in range(256)])
        border, _ = m.bytes_odds([prefix])
        whole = p[start + at].sum() + border[at]
        assert whole == pytest.approx(1, abs=1e-3)


def test_lm_weights_come_from_all_training_texts(spark):
    """The fitted step equals one taken over all texts at once, and each of many texts moves it."""
    import pyarrow as pa

    from thriftvec.llm.lm_score import FITTED, GATES, Tokens, fit

    r = random.Random(8)
    texts = [" ".join(r.choice(["a", "bc", "bc", "new", "old"]) for _ in range(r.randint(1, 9))) for _ in range(600)]

    def step(data):
        _, m = _small_model(True)
        before = m.weights.copy()
        fit(spark.createDataFrame([(t,) for t in data], "text string").repartition(3), m)
        return before, m.weights

    before, after = step(texts)
    _, m = _small_model(True)
    d = m.decide(Tokens(pa.array(texts)), alone=True)
    rows = [(g, float(y), *map(float, x)) for bits in d.all_bits() for g, y, *x in zip(np.minimum(bits.depth + 1, GATES - 1), bits.turn, *m.inputs(True)(bits), strict=True)]
    ask = np.flatnonzero(d.told.asked)
    rows += [(0, float(y), *map(float, x)) for y, *x in zip(d.told.hit[ask], *m.hints(d)(ask), strict=True)]
    want = before.astype(float)
    for g in {x[0] for x in rows}:
        y, x = np.array([v[1] for v in rows if v[0] == g]), np.array([[*v[2:], 1.0] for v in rows if v[0] == g])
        p = 1 / (1 + np.exp(-x @ want[g, :FITTED]))
        want[g, :FITTED] += np.clip(np.linalg.solve(np.eye(FITTED) + (x * (p * (1 - p))[:, None]).T @ x, (y - p) @ x), -1, 1)
    assert after == pytest.approx(want, abs=1e-3) and not np.array_equal(before, after)
    for i in (0, 300, 599):
        assert not np.array_equal(step(texts[:i] + ["bc new bc new bc new a a a a"] + texts[i + 1 :])[1], after)


def test_language(spark):
    from thriftvec.llm.langid import identify, train

    r = random.Random(1)
    syll = {"aa": ["ka", "lo", "mi"], "bb": ["str", "ent", "ung"], "cc": ["éu", "ça", "oî"]}
    make = lambda g: " ".join("".join(r.choice(syll[g]) for _ in range(r.randint(1, 4))) for _ in range(40))
    data = [(i, make(g), g) for i, g in enumerate(r.choice(list(syll)) for _ in range(150))]
    d = spark.createDataFrame(data + [(900, None, "aa"), (901, "123 !", None), (902, "", "bb")], "doc_id long, text string, lang string")
    m = train(d.where("doc_id % 3 <> 1"))
    got = {x["doc_id"]: x for x in identify(d, m).collect()}
    assert all(got[i]["_lang"] == g for i, _, g in data)
    assert [got[i]["_lang"] for i in (900, 901, 902)] == ["und"] * 3 and all(0 <= x["_score"] <= 1 for x in got.values())
    none = identify(d, train(d.limit(0))).collect()
    assert {x["_lang"] for x in none} == {"und"}


def test_html(spark):
    from thriftvec.llm.html_text import extract, main_text

    page = "<html><head><title>t</title><script>var a='<p>no</p>';</script></head><body><nav><a href='/'>home</a></nav><article><h1>A &amp; B</h1><p>One <b>bold</b>\n word.<p>Two&nbsp;three &#233;<br>four</article><div class='comments'><p>first! great post, thank you for this one</p></div><footer>&copy; x</footer>"
    assert main_text(page) == "A & B\n\nOne bold word.\n\nTwo three é four"
    d = spark.createDataFrame([(1, "u", page, "x"), (2, None, None, "x"), (2, None, None, "x"), (None, "v", "", "x")], "page_id long, url string, html string, text string")
    got = [r.asDict() for r in extract(d).collect()]
    assert len(got) == 4 and [g["_n_chars"] for g in got] == [len(g["_text"]) for g in got]
    assert extract(d.limit(0)).count() == 0


LONG = "some words of a paragraph that goes on " * 6


@pytest.mark.parametrize(
    "page,want",
    [
        ('<body class="has-sidebar"><article><p>One two three.</p></article>', "One two three."),
        ('<article class="post no-comments"><p>One two three.</p></article>', "One two three."),
        ('<div class="page with-header"><article><p>One two.</p><p>Three.</p></article></div>', "One two.\n\nThree."),
        (f"<body><div><a href=1>a</a> <a href=2>b</a></div><p>{LONG}</p></body>", LONG.strip()),
        ("plain  text\nonly", "plain text only"),
        ('<article><p class="a"b">Text of it</p></article>', "Text of it"),
        (f"<h1>Head</h1><p>{LONG}</p><p>{LONG}</p><div><a href=1>l1</a> | <a href=2>l2</a></div>", f"Head\n\n{LONG.strip()}\n\n{LONG.strip()}"),
        (f"<article><p>{LONG}</p></article><section id=comments><article><p>{LONG}</p></article></section>", LONG.strip()),
        (f"<div class='cookie-notice'><p>{LONG}</p></div><main><p>{LONG}</p><form><p>{LONG}</p></form></main><aside>{LONG}</aside>", LONG.strip()),
        (f"<div><p>{LONG}</p><p>{LONG}</p></div><ul><li><a href=1>one two</a></li><li><a href=2>three</a></li></ul>", f"{LONG.strip()}\n\n{LONG.strip()}"),
        ("<article><p>a &lt;b&gt; &amp;amp; c < d</p><!-- <p>no</p> --><p>x<style>p{}</style>y</p></article>", "a <b> &amp; c < d\n\nxy"),
    ],
)
def test_html_pages(page, want):
    from thriftvec.llm.html_text import main_text

    assert main_text(page) == want


def test_html_link_density():
    """Blocks without telling names or elements go by their links and by those around them."""
    from thriftvec.llm.html_text import main_text, model

    def used(t):
        return {t[0], *used(t[2]), *used(t[3])} if len(t) == 4 else set()

    assert {0, 1} <= used(model()[0]) and {2, 3, 4, 5} & used(model()[0])
    assert main_text(f"<p>{LONG}</p><div><a href=1>{LONG}</a></div><p>{LONG}</p>") == f"{LONG.strip()}\n\n{LONG.strip()}"


def test_html_odd_markup_is_linear():
    import time

    from thriftvec.llm.html_text import main_text

    for p in ("", "<", "<p", "<!--", "<script>", "a < b", '<p class="x>y', "</", "<a =b>", "<p a=>z", *(x * 20000 for x in ('<p a="', "<b></i>", "<!", "<svg>", "<p class='a\"", "<div>")), "<div>" * 20000 + "</p>" * 20000, "<i>" * 20000 + "</b>" * 20000):
        t = time.time()
        main_text(p)
        assert time.time() - t < 5


def test_audio(spark):
    from thriftvec.llm.audio import align, chroma, fingerprint, match, melody, prints, render

    r = np.random.default_rng(4)
    v = r.normal(size=64) * 0.12
    a = prints(chroma(melody(v)))
    noisy = melody(v).astype(float) + r.normal(size=64 * 256) * 600
    b = prints(chroma(np.r_[np.zeros(256 * 4), noisy]))
    off, over, err = align(a, b)
    assert off == 8 and over > 60 and err < 0.15
    assert align(a, prints(chroma(melody(r.normal(size=64) * 0.12))))[2] > 0.25
    assert len(prints(chroma(np.zeros(10)))) == 0 and align(a, a[:0]) == (0, 0, 1.0)
    x = [v, v, v + r.normal(size=64) * 0.002, r.normal(size=64) * 0.12]
    d = spark.createDataFrame([(i * 20, [float(c) for c in w]) for i, w in enumerate(x)] + [(81, None)], "id long, v array<double>")
    got = {m["id"]: m for m in match(fingerprint(render(d))).collect()}
    assert got[20]["class_id"] == 0 and got[0]["n_matches"] == (0 if got[40]["class_id"] == 0 else 1)
    assert got[60]["n_matches"] == 0 and got[81]["n_prints"] == 0 and got[81]["n_matches"] is None


def test_audio_recall(spark):
    """Noisy, cropped and shifted copies: nearly all that an alignment of all pairs matches are found, and nothing else."""
    from thriftvec.llm.audio import LEAST_OVERLAP, MOST_ERRORS, align, chroma, fingerprint, match, melody, prints, samples

    r = np.random.default_rng(8)
    media = []
    for g in range(30):
        clean = melody(r.normal(size=64) * 0.12).astype(float)
        media.append(clean)
        for k in range(4):
            x = clean + r.normal(size=len(clean)) * (300, 900, 1800, 3000)[k]
            x = x[: len(x) * 3 // 4] if k == 1 else np.r_[np.zeros(128 * (3 + k)), x] if k == 2 else x[640:] if k == 3 else x
            media.append(x)
    raw = [np.clip(x, -32768, 32767).astype("<i2").tobytes() for x in media]
    rows = [(20 * i if i % 5 == 0 else 20 * i + 1, b) for i, b in enumerate(raw)] + [(7001, b"abc"), (7002, None), (7003, raw[0] + b"x"), (None, raw[1])]
    found = fingerprint(spark.createDataFrame(rows, "id long, media binary"))
    got = {m["id"]: m for m in match(found).collect()}
    fp = {i: prints(chroma(samples(b))) for i, b in rows if i is not None}
    want = have = 0
    for i, p in fp.items():
        if i % 20 == 0:
            hits = set()
            for j, q in fp.items():
                if len(q) and q.tobytes() != p.tobytes():
                    _, over, err = align(p, q)
                    hits |= {q.tobytes()} if over >= LEAST_OVERLAP and err <= MOST_ERRORS else set()
            want, have = want + len(hits), have + got[i]["n_matches"]
            assert got[i]["n_matches"] <= len(hits)
    assert want >= 60 and have >= 0.9 * want
    assert got[7003]["class_id"] == 0 and got[7001]["n_prints"] == got[7002]["n_prints"] == 0
    assert match(fingerprint(spark.createDataFrame([], "id long, media binary"))).count() == 0


def test_ids_survive_nulls(spark):
    """Large ids beside a null one come back as they are; the pipeline keeps columns of any name."""
    import corpus_pipeline as cp
    from thriftvec.llm.mixing import mix_sources
    from thriftvec.llm.packing import pack_documents

    ids = [None, *((1 << 53) + 2 * i + 1 for i in range(9))]
    d = spark.createDataFrame([(i, f"some words {n} of a text", "en", "a") for n, i in enumerate(ids)], "doc_id long, text string, lang string, source string")
    key = lambda rows: sorted((r["doc_id"] for r in rows), key=lambda x: x or 0)
    assert key(mix_sources(d).collect()) == key(pack_documents(d).collect()) == key(d.collect())
    for c in ("_lang", "_score", "_id", "_th", "_copy", "_gone", "_copies", "_i", "_kept", "component_id", "copies", "other0", "c0", "g_id"):
        d = d.withColumn(c, F.lit(7))
    for _, f in cp.STAGES[:4]:
        out = f(spark, d, "")
        assert out.columns == d.columns and out.where("c0 = 7 and _gone = 7 and other0 = 7").count() == out.count()


def test_embeddings_of_any_length(spark):
    from thriftvec.llm.embeddings import near_duplicates

    rows = [(1, [1.0, 0.0, 0.0]), (2, [0.99, 0.01, 0.0]), (3, [0.0, 1.0, 0.0]), (4, [1.0, 1.0]), (5, [2.0, 2.0]), (6, [1e300, 1e300]), (7, [1e-300, 1.1e-300]), (8, [3.0]), (9, [5.0]), (10, [-1.0]), (11, [])]
    got = {g["vec_id"]: (g["n_links"], g["component_id"]) for g in near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (0, 3), 4: (3, 4), 5: (3, 4), 6: (3, 4), 7: (3, 4), 8: (1, 8), 9: (1, 8), 10: (0, 10), 11: (0, 11)}


def test_pipeline(spark, docs, rows, tmp_path):
    import corpus_pipeline as cp

    assert [n for n, _ in cp.STAGES] == ["language_id", "ngram_jaccard", "substring_dedup", "mix_sources", "bestfit_packing"]
    d = docs
    for k, (_, f) in enumerate(cp.STAGES):
        out = f(spark, d, "")
        if k < 4:
            assert out.columns == docs.columns
        out.write.parquet(str(tmp_path / str(k)))
        d = spark.read.parquet(str(tmp_path / str(k)))
        if k == 0:
            assert not {70, 71, 72} & {r["doc_id"] for r in d.collect()}
        if k == 1:
            assert not {73, 74, 76} & {r["doc_id"] for r in d.collect()}
    assert d.count() > 0
    docs.limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert cp.run(spark, str(tmp_path)).count() == 0


def test_jaccard_verifies_few_pairs_of_a_near_copy_group(spark, monkeypatch):
    """A group of near copies costs a few verified pairs a document, whatever n-grams they share; later rounds lose none."""
    from thriftvec.llm import jaccard

    r = random.Random(5)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(300):
        w = list(base)
        w[r.randrange(120)] = f"x{i}"
        rows.append((i, " ".join(w)))
    rows += [(1000 + i, f"own{i} " * 3 + " ".join(base[:20])) for i in range(5)]
    plain, counted = jaccard.stored, []

    def stored(df):
        out = plain(df)
        if df.columns == ["a", "b"]:
            counted.append(out.count())
        return out

    monkeypatch.setattr(jaccard, "stored", stored)
    got = {x["doc_id"]: x["component_id"] for x in jaccard.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {got[i] for i in range(300)} == {0} and len({got[1000 + i] for i in range(5)}) == 5
    assert counted[0] <= 2 * jaccard.PARTNERS * 300


def test_components_are_merged_by_further_links(spark):
    from thriftvec.llm.jaccard import _merged

    pairs = lambda x: spark.createDataFrame(x, "a long, b long")
    first = _merged(None, pairs([(5, 7), (7, 9), (20, 21)]))
    got = {r["node"]: r["component"] for r in _merged(first, pairs([(9, 21), (3, 4), (30, 7)])).collect()}
    assert got == {5: 5, 7: 5, 9: 5, 20: 5, 21: 5, 30: 5, 3: 3, 4: 3}


def test_audio_meetings_are_no_rows(spark, monkeypatch):
    """No join or shuffle of keys: blocks of queries go with the tasks, and several blocks give what one gives."""
    from thriftvec.llm import audio

    r = np.random.default_rng(6)
    rows = [(10 * i, [float(x) for x in np.repeat(r.normal(size=4) * 0.1, 16) + r.normal(size=64) * 0.01]) for i in range(60)]
    found = audio.fingerprint(audio.render(spark.createDataFrame(rows, "id long, v array<double>"))).cache()
    one = audio.match(found)
    assert "key" not in one._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(audio, "ASKED_BYTES", 2000)
    assert sorted(map(str, one.collect())) == sorted(map(str, audio.match(found).collect()))


def test_embeddings_travel_once(spark, monkeypatch):
    """Vectors are not copied for cells or pairs of chunks, whatever the number of chunks; chunks far apart lose no link."""
    from thriftvec.llm import embeddings

    r = np.random.default_rng(9)
    x = np.concatenate([c + r.normal(size=(60, 12)) * 0.15 for c in r.normal(size=(5, 12))])
    x[290:] = x[0] + r.normal(size=(10, 12)) * 0.001
    plain, plans = embeddings.stored, []

    def stored(df):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return plain(df)

    monkeypatch.setattr(embeddings, "stored", stored)
    monkeypatch.setattr(embeddings, "CHUNK", 16)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    frame = spark.createDataFrame([(i, [float(v) for v in a]) for i, a in enumerate(x)], "vec_id long, embedding array<float>")
    got = {g["vec_id"]: g for g in embeddings.near_duplicates(frame).collect()}
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before
    assert plans and not any("Generate" in p for p in plans)
    x = x.astype(np.float32).astype(np.float64)
    n = np.sqrt((x * x).sum(1))
    link = (x @ x.T) / np.outer(n, n) >= 0.9
    np.fill_diagonal(link, False)
    comp = np.arange(300)
    for _ in range(300):
        comp = np.array([min([comp[i], *comp[link[i]]]) for i in range(300)])
    assert 300 < link.sum() < 300 * 150
    assert all((got[i]["n_links"], got[i]["component_id"]) == (link[i].sum(), comp[i]) for i in range(300))


def test_embeddings_with_fewer_coordinates_than_blocks(spark):
    from thriftvec.llm.embeddings import near_duplicates

    turn = lambda d: [float(np.cos(np.radians(d))), float(np.sin(np.radians(d)))]
    rows = [(i, turn(d)) for i, d in enumerate((0, 25, 50, 77, 180, 204.5))]
    got = {g["vec_id"]: (g["n_links"], g["component_id"]) for g in near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    assert got == {0: (1, 0), 1: (2, 0), 2: (1, 0), 3: (0, 3), 4: (1, 4), 5: (1, 4)}


def test_audio_aligns_all_candidates_at_once(monkeypatch):
    """A recording's candidates are aligned together, exactly as one by one; held tones, silence and empty ones, too."""
    import pyarrow as pa
    from thriftvec.llm import audio

    r = np.random.default_rng(12)
    clean = [audio.melody(np.repeat(r.normal(size=8) * 0.1, 8)).astype(float) for _ in range(12)]
    asked = [audio.prints(audio.chroma(x)) for x in clean]
    asked += [np.zeros(40, np.uint32), np.full(150, asked[0][3]), np.empty(0, np.uint32), asked[1][30:], asked[2][[5]]]
    heard = [audio.prints(audio.chroma(x + r.normal(size=len(x)) * 900)) for x in clean] + [*asked, np.r_[asked[3][40:], asked[4]]]
    want = [[audio.align(q, y) for q in asked] for y in heard]
    rows = [(q, 100 + c, w[0], w[2]) for c, y in enumerate(want) for q, w in enumerate(y) if w[2] <= audio.MOST_ERRORS and w[1] >= audio.LEAST_OVERLAP]
    assert len(rows) > 20

    def one_by_one(*_):
        raise AssertionError("aligned one by one")

    monkeypatch.setattr(audio, "align", one_by_one)
    ids, batch = np.arange(len(asked)), pa.record_batch({"class_id": np.arange(len(heard)) + 100, "prints": [y.astype("<u4").tobytes() for y in heard]})
    got = [tuple(x.values()) for b in audio._matches(ids, [q.astype("<u4").tobytes() for q in asked])(iter([batch])) for x in b.to_pylist()]
    assert set(got) <= set(rows) and len(got) >= 0.9 * len(rows)
    one = audio._Asked(ids, asked)
    for votes in (1 << 21, 7):
        monkeypatch.setattr(audio, "VOTES", votes)
        assert [list(zip(*(x.tolist() for x in one.aligned(ids, y)), strict=True)) for y in heard] == want


def test_lm_decisions_by_depth(monkeypatch):
    """Decisions of one depth come together, so that slopes are sums over slices; they are those of text order."""
    import pyarrow as pa
    from thriftvec.llm import lm_score as lm

    r = random.Random(7)
    t = lm.Tokens(pa.array([" ".join(f"w{int(r.paretovariate(0.7)) % 90}" for _ in range(r.randrange(200))) for _ in range(40)] + [None, ""]))
    h, c = np.unique(t.hash, return_counts=True)
    o = np.argsort(-c, kind="stable")
    d = lm.Frame(lm.Tree(h[o], c[o], 0), lm.Phrases.empty(lm.PHRASES[0]), lm.SLOTS[0]).decide(t)
    monkeypatch.setattr(lm, "TOGETHER", 500)
    some = lambda b: sorted(zip(*(x.tolist() for x in (b.depth, b.node, b.turn, b.slot1, b.slot2)), strict=True))
    parts = list(d.by_depth())
    assert [some(b) for b, _ in parts] == [some(b) for b in d.all_bits()]
    assert all(b.depth.tolist() == np.repeat(np.arange(len(n)), n).tolist() for b, n in parts)


def test_ids_are_counted_as_texts_are_encoded():
    """One pass: the last row of a task holds the counts of its ids, in a column of its own."""
    import pyarrow as pa
    from thriftvec.llm.token_codec import _narrow
    from thriftvec.llm.tokens import default_path

    texts = ["a b", None, "x" * (1 << 20), "", "The cat, the $$$cat.\nEnd"]
    batches = [pa.RecordBatch.from_pydict({"doc_id": [i], "text": pa.array([t], pa.string())}) for i, t in enumerate(texts)]
    got = [r for b in _narrow(default_path("byte_bpe_50k.json"))(iter(batches)) for r in b.to_pylist()]
    assert [r["doc_id"] for r in got] == list(range(5)) and [r["counts"] is None for r in got] == [True] * 4 + [False]
    ids = np.frombuffer(b"".join(r["ids"] for r in got), "<u2")
    assert (np.frombuffer(got[-1]["counts"], "<i8") == np.bincount(ids, minlength=50257)).all()


def test_plain_texts_are_cut_by_string_methods(monkeypatch):
    """Known pieces of a plain text are found without the pattern; all pieces give the ids of the whole text."""
    from thriftvec.llm import tokens
    from tokenizers import Tokenizer

    path = tokens.default_path("byte_bpe_50k.json")
    e, t = tokens.SpanEncoder(path), Tokenizer.from_file(path)
    r = random.Random(6)
    marks = [" ", "  ", "\n", "\n\n", " \n", "\n ", ",", ".", "...", ", ", ". ", ".\n", "$$$ ", "!! ", "-", "_", "_,", " ,", "1,5", "3.", "\t", "'s ", "<|endoftext|>", "\u00a0", "\u0301,"]
    texts = ["".join(r.choice(["cat", "Dog", "\u00c9t\u00e9", "xyzzyq", "2"]) * r.randrange(2) + r.choice(marks[: r.choice([7, 25])]) for _ in range(r.randrange(12))) for _ in range(3000)]
    texts += [",", " ", ".a", ", a", "\n", "a\n", "a ", " a", "a,", "a.b,c\nd"]
    for _ in range(2):
        assert e.encode(texts) == [np.asarray(t.encode(x, add_special_tokens=False).ids, "<u4").tobytes() for x in texts]
    plain = "The cat, the dog.\nEnd of it."
    want = e.encode([plain])
    monkeypatch.setattr(tokens, "_PLAIN", None)
    assert e.encode([plain]) == want


def test_lm_tables_are_counted_in_small_parts(monkeypatch):
    """A task's tables are the same whatever its blocks are looked at in, and small parts take less memory."""
    import tracemalloc
    from types import SimpleNamespace

    import pyarrow as pa
    from thriftvec.llm import lm_score as lm

    r = random.Random(11)
    texts = [" ".join(f"w{int(r.paretovariate(0.7)) % 5000}" for _ in range(r.randrange(2000))) for _ in range(400)] + [None, ""]
    h, c = np.unique(lm.Tokens(pa.array(texts)).hash, return_counts=True)
    h, c = h[c > 2], c[c > 2]
    o = np.argsort(-c, kind="stable")
    shared = SimpleNamespace(value=lm.Frame(lm.Tree(h[o], c[o], 9), lm.Phrases.empty(lm.PHRASES[0]), lm.SLOTS[0]))
    monkeypatch.setattr(lm, "_part", lambda: 0)
    got, peaks = [], []
    for few in (lm.BLOCK, 1 << 17):
        monkeypatch.setattr(lm, "FEW", few)
        tracemalloc.start()
        got.append([b.to_pylist() for b in lm._tables(shared)(iter([pa.RecordBatch.from_pydict({"text": pa.array(texts, pa.string())})]))])
        peaks.append(tracemalloc.get_traced_memory()[1])
        tracemalloc.stop()
    assert got[0] == got[1] and peaks[1] < peaks[0] - 10e6


def test_lm_phrases_merge_without_joining_all(monkeypatch):
    from thriftvec.llm import lm_score as lm

    r = np.random.default_rng(2)
    e = np.zeros(5000, lm._ENTRY)
    for k, top in (("slot", 300), ("check", 3), ("follows", 4), ("seen", 50)):
        e[k] = r.integers(0, top, len(e)) + (k == "seen")
    want = lm._best_of_few(e)
    monkeypatch.setattr(lm, "AT_ONCE", 700)
    assert (lm._best([e[:1000], e[1000:1000], e[1000:]]) == want).all()


def test_lm_learns_through_whole_texts(monkeypatch):
    """Token by token, what a text has taught so far tells of the next, from its first token to its last."""
    import pyarrow as pa

    from thriftvec.llm import lm_score as lm

    r = random.Random(4)
    texts = [" ".join(r.choice("aaabcde") for _ in range(n)) for n in (0, 3, 300, 1, 450, 40)] + [None]
    _, m = _small_model(True)
    d = m.decide(lm.Tokens(pa.array(texts)))
    want, inputs, hints = [], m.inputs(), m.hints(d)
    for k in range(len(texts)):
        w = {g: m.weights[min(g, lm.GATES - 1)].astype(float) for g in range(40)}
        own, fine, log = Counter(), {}, 0.0
        for tok in np.flatnonzero(d.text == k).tolist():
            todo = []
            if d.told.asked[tok]:
                todo.append((0, float(d.told.hit[tok]), [float(v[0]) for v in hints(np.array([tok]))], 0))
            n = int(d.deep[tok])
            bits = d.bits(np.array([tok]), np.zeros(n, int), np.arange(n))
            todo += [(g + 1, float(y), x, int(s)) for g, (y, s, *x) in enumerate(zip(bits.turn, bits.node.astype(np.uint32) * lm._S >> np.uint32(24), *inputs(bits), strict=True))]
            learned = []
            for g, y, x, s in todo:
                x = np.array([*x, 1, own[s]], float)
                o = float(w[g] @ x)
                level = (g, int(min(max(o, -lm.LEVELS // 2), lm.LEVELS // 2 - 1)))
                p, q = 1 / (1 + math.exp(-o)), 1 / (1 + math.exp(-o) * fine.get(level, 1.0))
                log += math.log((p + q) / 2 if y else 1 - (p + q) / 2)
                learned.append((g, s, level, x, y - p, y - q))
            for g, s, level, x, e, e2 in learned:
                own[s] += lm.LEARN * e
                w[g] = w[g] + lm.RATE * e * x
                fine[level] = fine.get(level, 1.0) * (1 - lm.REFINE * e2)
        want.append(log)
    for lanes, ahead in ((1 << 11, 1 << 13), (2, 7)):
        monkeypatch.setattr(lm, "LANES", lanes)
        monkeypatch.setattr(lm, "AHEAD", ahead)
        assert lm.mix(d, inputs, hints, m.weights) == pytest.approx(want, rel=2e-4)


def test_lm_counts_all_phrases(monkeypatch):
    """The most frequent phrase of a slot, however texts are dealt, also where a task sees it once or another one more often."""
    import pyarrow as pa

    from thriftvec.llm import lm_score as lm

    r = random.Random(6)
    texts = [" ".join(f"w{int(r.paretovariate(0.8)) % 300}" for _ in range(r.randrange(30))) for _ in range(200)]
    size = lm.PHRASES[0]
    want = Counter()
    for t in texts:
        t = lm.Tokens(pa.array([t]))
        for ctx in t.contexts()[:2]:
            want.update(zip((ctx >> np.uint64(48)).tolist(), (ctx & np.uint64(0xFFFF)).tolist(), t.contexts()[2].tolist(), strict=True))
    most = {}
    for (slot, _, _), c in want.items():
        most[slot] = max(most.get(slot, 0), c)
    monkeypatch.setattr(lm, "_part", lambda: 0)

    def run(tasks, held, width):
        monkeypatch.setattr(lm, "HELD", held)
        sent = [b for i in range(tasks) for b in lm._phrases(size, width)(iter([pa.RecordBatch.from_pydict({"text": pa.array([t], pa.string())}) for t in texts[i::tasks]]))]
        got = {}
        for b in lm._most_seen(width)(b.select(["piece", "v"]) for b in sent):
            for x in b.to_pylist():
                for s, check, follows, seen in np.frombuffer(x["v"], lm._SENT).tolist():
                    assert x["piece"] * lm.PIECE + s not in got
                    got[x["piece"] * lm.PIECE + s] = (check, follows, seen)
        return got

    got = run(1, 1 << 20, lm.PIECE)
    assert {s: c for s, (_, _, c) in got.items()} == most
    assert all(want[s, check, follows] == c for s, (check, follows, c) in got.items())
    assert run(200, 1 << 20, 64) == run(7, 300, 1 << 12) == got


def test_lm_large_counts_keep_their_share():
    from thriftvec.llm.lm_score import HITS, SPELLED, Bits, Model, Phrases, Tree

    total = np.zeros(4 * 256 + SPELLED + 2 * HITS, np.uint32)
    total[:4] = total[512:516] = [100_000, 3_000_000, 7, 5]
    m = Model(Tree(np.array([1, 2], np.uint64), np.array([5, 3]), 1), Phrases.empty(1 << 10), total, 256)
    at = np.zeros(1, np.int32)
    far, near = (float(x[0]) for x in m.inputs()(Bits(at, at, at, at, at)))
    assert far == pytest.approx(math.log(30), abs=0.02) and near == pytest.approx(math.log(30), abs=0.02)
    assert m.near[1].tolist() == [7, 5]
