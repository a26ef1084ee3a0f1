"""HTML extraction by union-free wrappers.

Pages of one host are read as streams of block tags and text slots. A wrapper is a regular
expression without alternatives: tags, text slots, `( )?` groups and `( )+` groups. It
starts from one page and is aligned with the next, again and again; what one side has and
the other lacks becomes an optional group, neighbouring repeats become a repeated group.
Equal page shapes are folded first, so a host is a handful of shapes however many pages
it has.

A text of `WORDS` words or more that stands under one path on half of the host's pages
with that path, and on `PAGES` different pages at least, is template: it goes into the shapes as a
literal, `path#hash`. All other texts are slots. Shorter texts are always slots, as
pages may share a word or a subheading of their own. A page gives no literals, unless they are
most of its text: then it is a near copy of other pages and stays whole. Pages without
a host share no template.

A page gives every text block outside menus, headers, footers, sidebars, notices, adverts,
forms and comments that its host's wrapper doesn't show to be template.

Cases: null, empty or tagless html: empty text, or the bare text of a tagless page;
missing end tags, stray ones, comments and cut-off markup are read leniently; pages with
a null or broken url form the host ''; repeated rows each give a row; extra columns are
ignored.
"""

from __future__ import annotations

import html as entities
import json
import re
from collections.abc import Iterable, Iterator

import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WORDS, PAGES = 5, 3
# tags that end a block of text
BLOCKS = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head "
    "header hgroup hr html li main menu nav ol option p pre search section select summary table tbody td tfoot th thead title tr ul".split()
)
DROPPED = frozenset("nav header footer aside form menu dialog search head title button select option textarea noscript template iframe fieldset".split())
RAW = ("script", "style", "textarea", "title", "noscript", "template", "iframe", "svg", "math", "object")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
# names of classes, ids and roles of what isn't the article
ASIDE = re.compile(
    r"(?:^|[\s_-])(?:nav\w*|menu\w*|breadcrumbs?|header|masthead|footer|foot|sidebar\w*|side|aside|ads?|advert\w*|banner\w*|promo\w*|sponsor\w*|cookies?|consent|gdpr|notices?|"
    r"popup|modal|overlay|newsletter|subscribe|subscription|signup|login|share|sharing|social|comments?|commentlist|replies|reply|respond|disqus|discussion|related|recommend\w*|"
    r"widget\w*|toolbar|pagination|pager|skip\w*|search\w*|form|alert|disclaimer|complementary|contentinfo|navigation|dialog)(?:$|[\s_-]|\d)",
    re.I,
)
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
_ATTR = re.compile(r"\b(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
_SPACE = re.compile(r"\s+")
_ENDS_BY = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}


def _boilerplate(tag: str, attrs: str) -> bool:
    if tag in DROPPED:
        return True
    if not attrs or tag in ("html", "body", "article", "main"):
        return False
    for name, a, b, c in _ATTR.findall(attrs):
        name, value = name.lower(), a or b or c
        if name in ("class", "id", "role") and ASIDE.search(value):
            return True
        if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none", value, re.I):
            return True
    return False


def blocks(page: str) -> list[tuple[str, str, int, bool]]:
    """Text blocks in page order: (path of block tags, text, characters in links, in boilerplate)."""
    out: list[tuple[str, str, int, bool]] = []
    stack: list[tuple[str, str, bool]] = []  # tag, step of the path, boilerplate from here on
    parts: list[str] = []
    links = linked = 0

    def close() -> None:
        nonlocal linked
        if parts:
            text = _SPACE.sub(" ", "".join(parts)).strip()
            parts.clear()
            if text:
                out.append(("/".join(s for _, s, _ in stack if s), text, linked, bool(stack) and stack[-1][2]))
        linked = 0

    def text(raw: str) -> None:
        nonlocal linked
        if raw:
            plain = entities.unescape(raw) if "&" in raw else raw
            parts.append(plain)
            if links:
                linked += len(plain.strip())

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if not m:
            text(page[at:])
            break
        text(page[at : m.start()])
        at = m.end()
        tag = (m[2] or "").lower()
        if not tag:
            if m[0].startswith("<![CDATA["):
                text(m[0][9:].removesuffix("]]>"))
            continue
        end, attrs = bool(m[1]), m[3] or ""
        if not end and tag in RAW and not attrs.rstrip().endswith("/"):
            stop = re.compile(rf"</{tag}\b[^>]*(?:>|\Z)", re.I).search(page, at)
            if tag in BLOCKS:
                close()
            at = stop.end() if stop else n
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag == "a":
            links = 0 if end else 1
            continue
        if tag not in BLOCKS and not end:
            # inline elements matter only where they hide what they hold
            if tag not in VOID and not attrs.rstrip().endswith("/") and _boilerplate(tag, attrs):
                close()
                stack.append((tag, "", True))
            continue
        if tag not in BLOCKS:
            if stack and stack[-1][0] == tag:
                close()
                stack.pop()
            continue
        close()
        if tag == "hr":
            continue
        if not end:
            while stack and (stack[-1][0] in ("p", "h1", "h2", "h3", "h4", "h5", "h6") and (stack[-1][0] == "p" or tag[0] == "h" and tag[1:].isdigit()) or stack[-1][0] in _ENDS_BY.get(tag, ())):
                stack.pop()
            bad = bool(stack) and stack[-1][2] or _boilerplate(tag, attrs)
            stack.append((tag, tag + ("!" if bad else ""), bad))
        else:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    del stack[k:]
                    break
    close()
    return out


# ---- wrappers: a node is a string (path of a slot, or path#hash of a literal) or ["?", nodes] or ["+", nodes]


def fold(nodes: list) -> list:
    """Neighbouring equal runs become repeated groups, the shortest runs first."""
    changed = True
    while changed:
        changed = False
        for size in range(1, min(8, len(nodes) // 2) + 1):
            k, out = 0, []
            while k < len(nodes):
                unit = nodes[k : k + size]
                body = unit[0][1] if size == 1 and isinstance(unit[0], list) and unit[0][0] == "+" else unit
                e = k + size
                while len(unit) == size and nodes[e : e + size] in (unit, body, [["+", body]]):
                    e += size
                if e > k + size:
                    out.append(["+", body])
                    k, changed = e, True
                else:
                    out.append(nodes[k])
                    k += 1
            nodes = out
    return nodes


def _bare(node):
    return node[1] if isinstance(node, list) else [node]


def align(a: list, b: list) -> list:
    """The least wrapper found that takes both: matches kept, the rest of either side optional."""

    def same(x, y) -> bool:
        if isinstance(x, str) or isinstance(y, str):
            return x == y or isinstance(x, list) and _bare(x) == [y] or isinstance(y, list) and _bare(y) == [x]
        return x[1] == y[1]

    n, m = len(a), len(b)
    best = [[0] * (m + 1) for _ in range(n + 1)]
    for i in range(n - 1, -1, -1):
        for j in range(m - 1, -1, -1):
            best[i][j] = best[i + 1][j + 1] + 1 if same(a[i], b[j]) else max(best[i + 1][j], best[i][j + 1])
    out, i, j = [], 0, 0

    def lone(node):
        out.append(node if isinstance(node, list) and node[0] == "?" else ["?", [node]])

    while i < n or j < m:
        if i < n and j < m and same(a[i], b[j]):
            x, y = a[i], b[j]
            kinds = {z[0] for z in (x, y) if isinstance(z, list)}
            body = _bare(x) if isinstance(x, list) else _bare(y)
            out.append(["?", [["+", body]]] if kinds == {"?", "+"} else [kinds.pop(), body] if kinds else x)
            i, j = i + 1, j + 1
        elif j == m or i < n and best[i + 1][j] >= best[i][j + 1]:
            lone(a[i])
            i += 1
        else:
            lone(b[j])
            j += 1
    return fold(out)


def digest(path: str, text: str) -> int:
    """A signed 64-bit hash of a text under a path."""
    h = xxhash.xxh64_intdigest(f"{path}\0{text}".encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def literal(path: str, text: str) -> str:
    return f"{path}#{digest(path, text)}"


def shape(found: list[tuple[str, str, int, bool]], template: frozenset = frozenset()) -> list:
    return fold([p if not template or digest(p, t) not in template else literal(p, t) for p, t, *_ in found])


def expression(nodes: list) -> str:
    """The wrapper as text."""
    return " ".join(x if isinstance(x, str) else f"({expression(x[1])}){x[0]}" for x in nodes)


def slots(nodes: list) -> list[str]:
    return [s for x in nodes for s in ([x] if isinstance(x, str) else slots(x[1]))]


def own_text(good: list[tuple[str, str]], literals: set[str]) -> list[str]:
    """The texts that fill slots; all of them where literals are most of the page."""
    own = [t for p, t in good if not literals or literal(p, t) not in literals]
    return own if 2 * sum(map(len, own)) >= sum(len(t) for _, t in good) else [t for _, t in good]


def main_text(page: str | None, literals: set[str] = frozenset()) -> str:
    return "\n".join(own_text([(p, t) for p, t, _, bad in blocks(page or "") if not bad], literals))


def host(url):
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1), F.lit("")))


def templates(pages: DataFrame) -> DataFrame:
    """(host, template): hashes of the texts that a host's pages share under one path. pages: (h, x), host and html."""
    from ._shared import durable

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = set()
            for h, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                good = [(p, t) for p, t, _, bad in blocks(page or "") if not bad]
                # pages of equal text are one page
                x = digest("", "\n".join(t for _, t in good))
                for p, t in good:
                    slot = digest(p, "")
                    rows.add((h, slot, None, x))
                    if len(t.split(None, WORDS)) >= WORDS:
                        rows.add((h, slot, digest(p, t), x))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [()] * 4, (pa.string(), pa.int64(), pa.int64(), pa.int64()))], names=["h", "slot", "t", "x"])

    rows = pages.filter("h <> ''").mapInArrow(run, "h string, slot long, t long, x long").distinct()
    often = durable(rows.groupBy("h", "slot", "t").agg(F.count("*").alias("n")).filter(F.col("n") >= PAGES), "shared-texts")
    of = often.filter("t is null").select("h", "slot", F.col("n").alias("pages"))
    shared = often.filter("t is not null").join(of, ["h", "slot"]).filter("2 * n >= pages")
    # written, so that its size is known before pages would be dealt by host
    return durable(shared.groupBy("h").agg(F.collect_set("t").alias("template")).select(F.col("h").alias("host"), "template"), "templates")


def shapes(pages: DataFrame) -> DataFrame:
    """(host, shape, pages): the distinct page shapes of each host. pages: (h, x, template)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h, x, template = (c.to_pylist() for c in batch.columns)
            got = [json.dumps(shape(blocks(page or ""), frozenset(t or ()))) for page, t in zip(x, template)]
            yield pa.RecordBatch.from_arrays([pa.array(h, pa.string()), pa.array(got, pa.string())], names=["h", "s"])

    return pages.mapInArrow(run, "h string, s string").groupBy("h", "s").agg(F.count("*").alias("n"))


def infer(pages: DataFrame, salts: int = 16) -> DataFrame:
    """(host, wrapper, expression, literals). Shapes are merged in two steps, so that no task has all of a host's."""

    def merge(df: pd.DataFrame) -> pd.DataFrame:
        pages_of = df.groupby("s")["n"].sum()
        wrapper: list | None = None
        for s in sorted(pages_of.index, key=lambda s: (-pages_of[s], s)):
            nodes = json.loads(s)
            wrapper = nodes if wrapper is None else wrapper if wrapper == nodes else align(wrapper, nodes)
        return pd.DataFrame({"h": [df["h"].iloc[0]], "s": [json.dumps(wrapper or [])], "n": [int(df["n"].sum())]})

    def finish(df: pd.DataFrame) -> pd.DataFrame:
        got = merge(df)
        wrapper = json.loads(got["s"].iloc[0])
        literals = sorted({x for x in slots(wrapper) if "#" in x})
        return pd.DataFrame({"host": [got["h"].iloc[0]], "wrapper": [got["s"].iloc[0]], "expression": [expression(wrapper)], "literals": [literals]})

    src = pages.select(host(F.col("url").cast("string")).alias("h"), F.col("html").cast("string").alias("x"))
    found = shapes(src.join(templates(src), F.col("h") == F.col("host"), "left").select("h", "x", "template"))
    salted = found.withColumn("salt", F.pmod(F.xxhash64("s"), F.lit(salts)))
    part = salted.groupBy("h", "salt").applyInPandas(lambda df: merge(df), "h string, s string, n long")
    return part.groupBy("h").applyInPandas(lambda df: finish(df), "host string, wrapper string, expression string, literals array<string>")


def extract(pages: DataFrame, wrappers: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every page, by its host's wrapper."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [main_text(page, set(literals or ())) for page, literals in zip(*(c.to_pylist() for c in batch.columns[2:]))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(got, pa.string()), pa.array([len(t) for t in got], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    src = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("x"))
    joined = src.join(wrappers.select("host", "literals"), host(F.col("url")) == F.col("host"), "left")
    return joined.select("page_id", "url", "x", "literals").mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op7_html(pages: DataFrame) -> DataFrame:
    from ._shared import durable

    return extract(pages, durable(infer(pages), "wrappers"))
