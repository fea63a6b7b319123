"""Main text of HTML pages: flat text blocks judged by a decision tree.

A page is read once into flat blocks of text between block-level tags. A block's features are its words and link density,
those of the blocks before and after, the kind of element it stands in, and the weight of the names (class, id, role)
around it, which is learned, too. A decision tree grown on a small labelled table tells main text from the rest; the table
is laid out by the rule of `labelled_pages`.

At 100 TB: a map over whole pages without shuffle, in time linear in a page whatever its markup; the tree is a few numbers.
"""

from __future__ import annotations

import html
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import blocks

# fixed values: element names of HTML by their part in a page
BLOCK_TAGS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split())
SILENT_TAGS = frozenset("script style noscript template svg iframe object canvas audio video title select option textarea button math".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CHROME_TAGS = frozenset("nav footer aside form menu dialog fieldset".split())
CLOSES_P = BLOCK_TAGS - {"html", "body", "title"}

_OPEN = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_BARE = re.compile(r"[^>\"'=]*>")
_GAP = re.compile(r"[\s/]*")
_KEY = re.compile(r"[^\s/>][^\s/>=]*")
_EQUALS = re.compile(r"\s*=\s*")
_VALUE = re.compile(r"[^\s>]*")
_PART = re.compile(r"[a-z0-9]+")
_CAMEL = re.compile(r"(?<=[a-z0-9])(?=[A-Z])")
DENIED = frozenset(("has", "no", "with", "without", "is", "not", "hide", "hidden"))  # a name behind one of these tells of another element
FEATURES = 13


def _attributes(page: str, at: int, ends: dict[str, bool]) -> tuple[list[str], int]:
    """Values of class, id and role of the tag whose name ends at `at`, and where the tag ends. `ends` remembers which
    quotes no longer occur, so that unclosed ones cost one look ahead for the whole page."""
    size = len(page)
    m = _BARE.match(page, at)
    if m:
        return [], m.end()
    names = []
    while at < size:
        at = _GAP.match(page, at).end()
        if at >= size:
            break
        if page[at] == ">":
            return names, at + 1
        key = _KEY.match(page, at)
        at = key.end()
        eq = _EQUALS.match(page, at)
        if not eq:
            continue
        at = eq.end()
        quote = page[at : at + 1]
        if quote in ('"', "'") and quote:
            z = -1 if ends.get(quote) else page.find(quote, at + 1)
            if z < 0:  # never closed: the value ends with the tag
                ends[quote] = True
                z = page.find(">", at)
                z = size if z < 0 else z
                value, at = page[at + 1 : z], z
            else:
                value, at = page[at + 1 : z], z + 1
        else:
            v = _VALUE.match(page, at)
            value, at = v.group(0), v.end()
        if key.group(0).lower() in ("class", "id", "role"):
            names.append(value)
    return names, size


def name_parts(values: list[str]) -> set[str]:
    """Words of class, id and role values; those that deny or announce another element are left out."""
    out: set[str] = set()
    for value in values:
        for word in value.split():
            parts = _PART.findall(_CAMEL.sub(" ", word).lower())
            if not set(parts) & DENIED:
                out.update(parts)
    return out


@dataclass
class Block:
    """A run of text between block-level tags: its characters in links, whether it stands in a chrome element, in an article
    element, in a heading, and the names of the elements around it, innermost last."""

    text: str
    linked: int
    chrome: int
    article: int
    heading: int
    names: tuple


def page_blocks(page: str) -> list[Block]:
    """The blocks with text, in page order; one pass, linear in the page whatever its markup."""
    out: list[Block] = []
    parts: list[str] = []
    linked = 0
    stack: list[tuple] = []  # tag, and the state outside of it
    depth: Counter = Counter()  # open elements by tag
    state = (0, 0, 0, 0, ())  # chrome, article, heading, link, names
    then = state
    ends: dict[str, bool] = {}

    def flush():
        nonlocal linked
        if parts:
            text = " ".join("".join(parts).split())
            if text:
                out.append(Block(text, linked, then[0], then[1], then[2], then[4]))
            parts.clear()
        linked = 0

    at, size = 0, len(page)
    while at < size:
        z = page.find("<", at)
        if z != at:
            raw = page[at:] if z < 0 else page[at:z]
            at = size if z < 0 else z
            if "&" in raw:
                raw = html.unescape(raw)
            then = state
            parts.append(raw)
            if state[3]:
                linked += len(raw.strip())
            continue
        m = _OPEN.match(page, at)
        if m is None:
            if page.startswith("<!--", at):
                z = page.find("-->", at + 4)
                at = size if z < 0 else z + 3
            elif page.startswith(("<!", "<?", "</"), at):
                z = page.find(">", at)
                at = size if z < 0 else z + 1
            else:
                parts.append("<")
                then = state
                at += 1
            continue
        tag = m.group(2).lower()
        names, at = _attributes(page, m.end(), ends)
        if m.group(1):
            if tag in BLOCK_TAGS:
                flush()
            if depth[tag]:
                while stack:
                    last, state = stack.pop()
                    depth[last] -= 1
                    if last == tag:
                        break
            continue
        if tag in ("br", "wbr"):
            parts.append(" ")
            continue
        if tag == "head":
            continue
        if tag in SILENT_TAGS:
            z = None if ends.get(tag) else re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            if z:
                at = z.end()
            else:
                ends[tag] = True
                at = size if tag in ("script", "style") else at
            continue
        if tag in BLOCK_TAGS:
            flush()
            if tag in CLOSES_P and stack and stack[-1][0] == "p":
                depth["p"] -= 1
                state = stack.pop()[1]
        if tag in VOID_TAGS:
            continue
        stack.append((tag, state))
        depth[tag] += 1
        chrome, article, heading, link, around = state
        if tag in CHROME_TAGS or (tag == "header" and not article):
            chrome = 1
        if tag in ("article", "main"):
            article = 1
        if len(tag) == 2 and tag[0] == "h" and tag[1] in "123456":
            heading = 1
        if tag == "a":
            link = 1
        if names and tag not in ("html", "body"):  # those of the whole page describe its layout
            mine = name_parts(names) - ({"header"} if article else set())
            if mine and len(around) < 64:
                around = (*around, frozenset(mine))
        state = (chrome, article, heading, link, around)
    flush()
    return out


def name_weights(pages: list[tuple[list[Block], list[bool]]]) -> dict[str, float]:
    """Log odds of main text for each name, from labelled pages."""
    main, rest = Counter(), Counter()
    for found, ys in pages:
        for b, y in zip(found, ys, strict=True):
            for x in set().union(*b.names):
                (main if y else rest)[x] += 1
    return {x: math.log((main[x] + 0.5) / (rest[x] + 0.5)) for x in main | rest}


def features(found: list[Block], weights: dict[str, float]) -> np.ndarray:
    """Per block: words and link density of it, of the block before and of the one after; chrome element, article element,
    heading, lowest and highest weight of the names around, whether the page has an article element, copyright sign."""
    x = np.zeros((len(found), FEATURES))
    if not found:
        return x
    n = np.array([len(b.text.split()) for b in found], float)
    d = np.array([min(1.0, b.linked / len(b.text)) for b in found], float)
    x[:, 0], x[:, 1] = n, d
    x[1:, 2], x[1:, 3], x[:-1, 4], x[:-1, 5] = n[:-1], d[:-1], n[1:], d[1:]
    x[:, 6:9] = [(b.chrome, b.article, b.heading) for b in found]
    seen: dict[tuple, tuple[float, float]] = {}
    for b in found:
        if b.names not in seen:
            w = [weights.get(v, 0.0) for v in set().union(*b.names)]
            seen[b.names] = (min(w, default=0.0), max(w, default=0.0))
    x[:, 9:11] = [seen[b.names] for b in found]
    x[:, 11] = x[:, 7].max()
    x[:, 12] = [b.text.startswith(("©", "(c)", "Copyright")) for b in found]
    return x


DEPTH, LEAST = 9, 12  # of the tree; blocks in a leaf


def grow(x: np.ndarray, y: np.ndarray, depth: int = DEPTH) -> tuple:
    """Decision tree by Gini impurity: (feature, threshold, below or equal, above) or (share of main text,)."""
    if depth == 0 or len(set(y.tolist())) < 2:
        return (float(y.mean()) if len(y) else 0.0,)
    best = None
    for f in range(x.shape[1]):
        o = np.argsort(x[:, f], kind="stable")
        v, c = x[o, f], np.cumsum(y[o])
        k = np.flatnonzero(v[1:] > v[:-1]) + 1
        k = k[(k >= LEAST) & (k <= len(y) - LEAST)]
        if not len(k):
            continue
        n = len(y)
        p, q = c[k - 1] / k, (c[-1] - c[k - 1]) / (n - k)
        g = k * p * (1 - p) + (n - k) * q * (1 - q)
        i = int(np.argmin(g))
        if best is None or g[i] < best[0] - 1e-12:
            best = (g[i], f, (v[k[i] - 1] + v[k[i]]) / 2)
    if best is None:
        return (float(y.mean()),)
    _, f, t = best
    low = x[:, f] <= t
    return (f, float(t), grow(x[low], y[low], depth - 1), grow(x[~low], y[~low], depth - 1))


def judge(tree: tuple, row: np.ndarray) -> bool:
    while len(tree) == 4:
        tree = tree[2] if row[tree[0]] <= tree[1] else tree[3]
    return tree[0] >= 0.5


# The labelled pages: what their elements are called (fixed values, as pages commonly name them) and how they are laid out.
OTHER_NAMES = "ad ads advert advertisement banner breadcrumb breadcrumbs byline captcha comment comments consent cookie copyright disclaimer feedback footer form gdpr header login masthead menu modal nav navbar navigation newsletter notice notification pagination popup popular promo promoted recommended related reply respond search share sharing sidebar signup social sponsor sponsored subscribe tags toolbar trending widget".split()
MAIN_NAMES = "article body content entry main page post story text".split()


def labelled_pages(pages: int = 1600, seed: int = 7) -> list[str]:
    """Pages laid out by rule with lengths drawn at random. Blocks that start with `*` are main text."""
    r = random.Random(seed)

    def run(low: int, high: int) -> str:
        return " ".join(f"w{i}" for i in range(r.randint(low, high)))

    def links(n: int, tag: str = "li") -> str:
        return "".join(f"<{tag}><a href='/{i}'>{run(1, 6)}</a></{tag}>" for i in range(n))

    def other(tagged: bool) -> str:
        """Something beside the text: by its element, by its name, or told by its links alone."""
        kind = r.randrange(5 if tagged else 3)
        text = r.choice([lambda: f"<p>{run(1, 60)}</p>", lambda: f"<p>{run(40, 220)}</p>", lambda: f"<h3>{run(1, 4)}</h3><ul>{links(r.randint(2, 6))}</ul>", lambda: f"<p>{run(5, 30)}</p><p>{run(1, 40)}</p>", lambda: f"<a href='/'>{run(1, 9)}</a> {run(1, 6)}"])()
        if kind == 0:
            return f"<ul>{links(r.randint(3, 8))}</ul>"
        if kind == 1:
            line = f"<div>{run(1, 8)}</div>" if r.random() < 0.6 else ""
            return f"<div>{links(r.randint(2, 5), 'span')}</div>{line}<div>{links(r.randint(2, 5), 'span')}</div>"
        if kind == 2:
            name = r.choice(OTHER_NAMES)
            return f"<{(e := r.choice(['div', 'section', 'p' if text[1] == 'a' else 'div']))} {r.choice(['class', 'id'])}='{name}'>{text}</{e}>"
        e = r.choice(["nav", "aside", "form", "footer", "dialog"])
        return f"<{e}>{text}</{e}>"

    def main(n: int, whole: bool) -> str:
        """Paragraphs; `whole`: they stand in an article element, which may hold other things, too."""
        out = [f"<h1>*{run(1, 12)}</h1>"] if r.random() < 0.8 else []
        for i in range(n):
            k = r.random()
            if k < 0.2:
                out.append(f"<p>*{run(1, 8)}</p>" + (f"<p>*{run(16, 80)}</p>" if not whole else ""))
            elif k < 0.3 and i:
                out.append(f"<h2>*{run(1, 8)}</h2><p>*{run(25, 80)}</p>")
            elif k < 0.4 and i:
                out.append("<ul>" + "".join(f"<li>*{run(1, 14)}</li>" for _ in range(3)) + f"</ul><p>*{run(20, 50)}</p>")
            elif k < 0.6:
                out.append(f"<p>*{run(15, 60)} <a href='/x'>{run(1, 4)}</a> {run(4, 20)}</p>")
            else:
                out.append(f"<p>*{run(16, 220)}</p>")
            if whole and r.random() < 0.12:
                out.append(other(True))
        return "".join(out)

    made = []
    for i in range(pages):
        whole = i % 2 == 0
        body = main(r.randint(1, 7), whole)
        if whole:
            e = r.choice(["article", "main"])
            body = f"<{e}{r.choice(['', ' class=post', ' class=entry'])}>{body}</{e}>"
            if r.random() < 0.5:
                body = f"<div>{run(2, 40)}</div>{body}"
            if r.random() < 0.5:
                body += f"<div>{run(2, 40)}</div>"
        elif r.random() < 0.6:
            body = f"<div class='{r.choice(MAIN_NAMES)}'>{body}</div>"
        if i % 10 == 9:
            made.append(f"*{run(1, 200)}")  # a page without any markup
            continue
        before = "".join(other(True) for _ in range(r.randint(0, 3)))
        after = "".join(other(True) for _ in range(r.randint(0, 3)))
        if r.random() < 0.5:
            after += f"<div class='comments'>{''.join(f'<{t}><p>{run(3, 160)}</p></{t}>' for t in [r.choice(['article', 'div', 'li'])] * 3)}</div>"
        if r.random() < 0.5:
            after += f"<p>&copy; {run(2, 20)}</p>"
        made.append(f"<html><head><title>{run(2, 5)}</title></head><body>{before}{body}{after}</body></html>")
    return made


@cache
def model() -> tuple[tuple, dict[str, float]]:
    """Tree and name weights, grown on the labelled pages."""
    pages = []
    for page in labelled_pages():
        found = page_blocks(page)
        ys = [b.text.startswith("*") for b in found]
        for b in found:
            b.text = b.text.removeprefix("*")
        pages.append((found, ys))
    weights = name_weights(pages)
    x = np.concatenate([features(f, weights) for f, _ in pages])
    return grow(x, np.concatenate([ys for _, ys in pages]).astype(float), DEPTH), weights


def main_text(page: str | None, trained: tuple | None = None) -> str:
    tree, weights = trained or model()
    found = page_blocks(page or "")
    x = features(found, weights)
    return "\n\n".join(b.text for b, row in zip(found, x, strict=True) if judge(tree, row))


def _extract(trained: tuple, keys: list[str], fields: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "html"):
            texts = [main_text(p, trained) for p in b.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema=fields)

    return run


def extract(pages: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """pages with a column html -> columns `keep` (default page_id, url), _text, _n_chars.

    Null or empty html, and pages without main text, give an empty text. Repeated rows are treated alike; markup that
    is cut off or not closed ends where the page ends. An empty table gives an empty result. Other columns are ignored.
    """
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    keep = [c for c in keep or ["page_id", "url"] if c.lower() not in ("_text", "_n_chars")]
    names = [f"c{i}" for i in range(len(keep))]
    d = pages.select(*(F.col(c).alias(n) for c, n in zip(keep, names, strict=True)), F.col("html").alias("html"))
    schema = T.StructType([d.schema[n] for n in names] + [T.StructField("_text", T.StringType()), T.StructField("_n_chars", T.LongType())])
    return d.mapInArrow(_extract(model(), names, to_arrow_schema(schema)), schema).withColumnsRenamed(dict(zip(names, keep, strict=True)))
