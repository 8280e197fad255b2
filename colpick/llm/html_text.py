"""Main text of web pages, with a suffix array over the pages of a host for boilerplate.

A page is parsed into blocks of text, each with the containers around it.  What
stands in an article, or in the main element, is the main text; what stands in
a menu, header, footer, sidebar, form, advert, notice or comment section is
not.  For the other blocks of pages without an article the host decides: the
token streams of its distinct pages are concatenated, a suffix array over them
finds long substrings that repeat on several pages, and covered tokens are
removed, as are whole blocks that repeat; what is left, in unique runs, is kept.

Only blocks outside articles enter the array: a passage that several articles
share is part of each of them.  A host of many pages isn't gathered in one
task: digests of its blocks and windows are counted by group-bys and joined
back, with the same result.
"""

from __future__ import annotations

import hashlib
import html as html_lib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import near_copies
from .common import batch_of, durable, text_key

# Elements of HTML by their role.
SILENT = {"script", "style", "noscript", "template", "svg", "head", "iframe", "object", "canvas", "select", "button", "textarea", "math"}
RAW = {"script", "style", "textarea", "title", "noscript", "iframe"}
CHROME = {"nav", "header", "footer", "aside", "form", "menu", "dialog"}
MAIN = {"article", "main"}
BLOCK = {"p", "div", "section", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol", "li", "dl", "dt", "dd", "table", "tr", "td", "th", "thead", "tbody", "tfoot", "caption", "blockquote", "pre", "figure", "figcaption", "hr", "br", "address", "details", "summary", "fieldset", "legend", "body", "html", "center", "option", "video", "audio"} | CHROME | MAIN | SILENT
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
#: Ends of elements that HTML lets authors leave out.
CLOSED_BY = {"p": BLOCK - {"br", "body", "html"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "option": {"option"}}
CHROME_NAMES = re.compile(r"(?:^|[\s_-])(?:ad|ads|advert\w*|adbox|banner|sponsor\w*|promo\w*|cookie\w*|consent|notice|gdpr|popup|modal|newsletter|subscribe|nav\w*|menu|breadcrumb\w*|sidebar|side|footer|foot|header|masthead|comment\w*|disqus|replies|reply|social|share|sharing|related|recommend\w*|widget|pagination|pager|toolbar|login|search)(?:$|[\s_-])", re.I)
#: An article of such a name is a reader's comment, not the page's.
COMMENT_NAMES = re.compile(r"(?:^|[\s_-])(?:comment\w*|disqus|replies|reply)(?:$|[\s_-])", re.I)
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|</?[a-zA-Z](?:[^<>\"']|\"[^\"]*\"|'[^']*')*>|</?[a-zA-Z][^<>]*>|[^<]+|<", re.S)
NAME = re.compile(r"</?([a-zA-Z][^\s/>]*)")
ATTRIBUTE = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))", re.I)
HIDDEN = re.compile(r"\s(?:hidden(?:[\s=>/]|$)|aria-hidden\s*=\s*[\"']?true)", re.I)
WHITE = re.compile(r"\s+")


def parse(html: str | None) -> tuple[list[str], list[str]]:
    """(blocks of the main text, other blocks that no container settles), white space in each turned into one space."""
    html = html or ""
    stack: list[tuple[str, int]] = []  # (element, role of what it holds)
    main, rest, held = [], [], []
    OPEN, INSIDE, OUT = 0, 1, 2
    role = OPEN
    at = 0

    def flush():
        if held:
            text = WHITE.sub(" ", "".join(held)).strip()
            held.clear()
            if text and role != OUT:
                (main if role == INSIDE else rest).append(text)

    for m in TOKEN.finditer(html):
        if m.start() < at:
            continue
        token = m.group()
        if token[0] != "<" or token == "<":
            if role != OUT:
                held.append(html_lib.unescape(token))
            continue
        if token.startswith("<![CDATA["):
            if role != OUT:
                held.append(token[9:-3])
            continue
        if token[1] in "!?":
            continue
        name = NAME.match(token)[1].lower()
        if token[1] == "/":
            if name in BLOCK:
                flush()
            places = [i for i, (n, _) in enumerate(stack) if n == name]
            if places:
                del stack[places[-1] :]
                role = stack[-1][1] if stack else OPEN
            continue
        if name in BLOCK:
            flush()
        while stack and name in CLOSED_BY.get(stack[-1][0], ()):
            stack.pop()
            role = stack[-1][1] if stack else OPEN
        if name in VOID or token.endswith("/>"):
            continue
        now = role
        if role != OUT:
            if name in SILENT or (name in CHROME and not (name == "header" and role == INSIDE)):
                now = OUT
            elif name not in ("body", "html") and (HIDDEN.search(token) or any((COMMENT_NAMES if name in MAIN else CHROME_NAMES).search(a or b or c) for a, b, c in ATTRIBUTE.findall(token))):
                now = OUT
            elif name in MAIN and role == OPEN:
                now = INSIDE
        if now != role:
            flush()
        stack.append((name, now))
        role = now
        if name in RAW:
            end = re.compile(rf"</{name}\b", re.I).search(html, m.end())
            at = end.start() if end else len(html)
            if role != OUT:
                held.append(html_lib.unescape(html[m.end() : at]))
    flush()
    return main, rest


def suffix_array(x: np.ndarray) -> np.ndarray:
    """Starts of the suffixes of a sequence of numbers in order, by prefix doubling."""
    n = len(x)
    rank = np.unique(x, return_inverse=True)[1].astype(np.int64) if n else x.astype(np.int64)
    width = 1
    while n:
        after = np.zeros(n, dtype=np.int64)
        after[: max(0, n - width)] = rank[width:] + 1
        key = rank * (n + 2) + after
        order = np.argsort(key, kind="stable")
        new = np.empty(n, dtype=np.int64)
        new[order] = np.concatenate(([0], np.cumsum(key[order][1:] != key[order][:-1])))
        rank = new
        if rank.max() == n - 1 or width > n:
            return order
        width *= 2
    return np.empty(0, dtype=np.int64)


def repeated_tokens(pages: list[list[str]], least: int = 6, kinds: list | None = None, spread: int = 2) -> list[np.ndarray]:
    """For each page's tokens, whether a substring of ``least`` or more covers it that ``spread`` pages of the list have.

    ``kinds`` names the group of copies of each page, and groups are counted in place of pages.
    """
    names: dict[str, int] = {}
    group = np.unique(kinds, return_inverse=True)[1] if kinds else np.arange(len(pages))
    stream, owner = [], []
    for k, tokens in enumerate(pages):
        stream += [names.setdefault(t, len(names)) for t in tokens]
        stream.append(-1 - k)  # a mark of its own after each page: no match goes across
        owner += [int(group[k])] * (len(tokens) + 1)
    x, of = np.array(stream, dtype=np.int64), np.array(owner, dtype=np.int64)
    covered = np.zeros(len(x) + 1, dtype=np.int64)
    if len(pages) > 1 and len(x) > least:
        order = suffix_array(x)
        # neighbours in the array that agree in ``least`` tokens stand in one run; a run on enough pages is boilerplate
        same = np.ones(len(order) - 1, dtype=bool)
        padded = np.append(x, np.arange(-1 - len(pages) - least, -1 - len(pages)))
        for j in range(least):
            same &= padded[order[1:] + j] == padded[order[:-1] + j]
        run = np.concatenate(([0], np.cumsum(~same)))
        met = np.unique(run * len(pages) + of[order]) // max(1, len(pages))
        start = order[(np.bincount(met, minlength=run[-1] + 1) >= spread)[run]]
        np.add.at(covered, start, 1)
        np.add.at(covered, np.minimum(start + least, len(x)), -1)
    inside = np.cumsum(covered[:-1]) > 0
    edges = np.cumsum([0, *[len(p) + 1 for p in pages]])
    return [inside[a : b - 1] for a, b in zip(edges, edges[1:])]


def repeated_blocks(pages: list[list[str]], kinds: list, least: int, spread: int) -> set[str]:
    """Blocks of ``least`` tokens or more that stand on pages of ``spread`` groups of copies."""
    on: dict[str, set] = {}
    for page, kind in zip(pages, kinds):
        for b in page:
            on.setdefault(b, set()).add(kind)
    return {b for b, k in on.items() if len(k) >= spread and b.count(" ") + 1 >= least}


def without(blocks: list[str], mark: np.ndarray) -> str:
    """Blocks less their marked tokens, joined by a newline; empty blocks go."""
    at, kept = 0, []
    for b in blocks:
        words = b.split(" ")
        left = [t for t, gone in zip(words, mark[at : at + len(words)].tolist()) if not gone]
        at += len(words)
        if left:
            kept.append(" ".join(left))
    return "\n".join(kept)


def unique_runs(pages: list[list[str]], kinds: list, least: int, long: int, spread: int) -> list[str]:
    """Texts of distinct pages of a host without what repeats: whole blocks of ``least`` tokens, other substrings of ``long``."""
    whole = repeated_blocks(pages, kinds, least, spread)
    marks = repeated_tokens([[t for b in page for t in b.split(" ")] for page in pages], long, kinds, spread)
    out = []
    for page, mark in zip(pages, marks):
        of = np.array([b in whole for b in page for _ in range(b.count(" ") + 1)], dtype=bool)
        out.append(without(page, mark | of))
    return out


def _passages(least: int, long: int):
    """Kernel over (host, tk, kind, rest): digest, first token and length of each whole block and each window of a page."""
    schema = pa.schema([("host", pa.string()), ("tk", pa.binary()), ("kind", pa.binary()), ("h", pa.binary()), ("at", pa.int32()), ("n", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for host, tk, kind, rest in zip(*(c.to_pylist() for c in batch.columns)):
                digest = lambda mark, s: hashlib.md5((mark + s).encode()).digest()
                words = [t for b in rest for t in b.split(" ")]
                found, at = [], 0
                for b in rest:
                    n = b.count(" ") + 1
                    if n >= least:
                        found.append((digest("b", b), at, n))
                    at += n
                found += [(digest("w", " ".join(words[i : i + long])), i, long) for i in range(len(words) - long + 1)]
                if found:
                    h, first, n = zip(*found)
                    yield batch_of(schema, [host] * len(h), [tk] * len(h), [kind] * len(h), h, first, n)

    return run


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("host", pa.string()), ("tk", pa.binary()), ("text", pa.string())])
    for batch in batches:
        if batch.num_rows:
            texts = []
            for rest, hits in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                mark = np.zeros(sum(b.count(" ") + 1 for b in rest), dtype=bool)
                for x in hits or ():
                    mark[x["at"] : x["at"] + x["n"]] = True
                texts.append(without(rest, mark))
            yield batch_of(schema, batch.column(0), batch.column(1), texts)


def extract(pages: DataFrame, host_pages: int = 1000, least: int = 6, long: int = 30, spread: int = 3, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every row: the main text, its blocks in page order joined by a newline.

    Null or empty html gives an empty text; a null url is a host of its own;
    null or repeated ids keep their rows.  A page with an article keeps all of
    it and nothing else.  Elsewhere a block of ``least`` tokens goes as a whole,
    and a substring of ``long`` from the middle of blocks, if it stands on pages
    of ``spread`` different groups; equal pages and near copies are one group.
    Hosts of more than ``host_pages`` distinct pages are counted, not gathered.
    """

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("main", pa.string()), ("rest", pa.list_(pa.string()))])
        for batch in batches:
            main, rest = [], []
            for page in batch.column(2).to_pylist():
                a, b = parse(page)
                main.append("\n".join(a) if a else None)
                rest.append(None if a else b)
            yield batch_of(schema, batch.column(0), batch.column(1), main, rest)

    def by_host(frame):
        import pandas as pd

        texts = unique_runs([list(x) for x in frame["rest"]], list(frame["kind"]), least, long, spread)
        return pd.DataFrame({"host": frame["host"], "tk": frame["tk"], "text": texts})

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html"))
    parsed = rows.mapInArrow(split, "page_id long, url string, main string, rest array<string>")
    settled = parsed.where("main is not null or size(rest) = 0").select("page_id", "url", F.coalesce("main", F.lit("")).alias("text"))
    host = F.coalesce(F.lower(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1)), F.lit(""))
    opened = parsed.where("main is null and size(rest) > 0").select("page_id", "url", "rest", host.alias("host"), text_key(F.concat_ws("\n", "rest")).alias("tk"))
    opened = durable(opened)
    if opened.isEmpty():
        return settled.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
    # a page counts once, however often it was crawled, and near copies of it are of its kind
    single = durable(opened.select("host", "tk", "rest").dropDuplicates(["host", "tk"]))
    near = near_copies.groups(single.dropDuplicates(["tk"]).select("tk", F.concat_ws(" ", "rest").alias("text")))
    single = durable(single.join(near, "tk", "left").select("host", "tk", F.coalesce("root", "tk").alias("kind"), "rest"))
    sizes = single.groupBy("host").agg((F.count("*") > host_pages).alias("large"))
    small = single.join(sizes.where("not large"), "host", "left_semi").groupBy("host").applyInPandas(by_host, "host string, tk binary, text string")
    large = single.join(sizes.where("large"), "host", "left_semi")
    passages = large.select("host", "tk", "kind", "rest").mapInArrow(_passages(least, long), "host string, tk binary, kind binary, h binary, at int, n int")
    often = passages.select("host", "h", "kind").distinct().groupBy("host", "h").count().where(F.col("count") >= spread)
    hits = passages.join(often, ["host", "h"], "left_semi").groupBy("host", "tk").agg(F.collect_list(F.struct("at", "n")).alias("hits"))
    counted = large.join(hits, ["host", "tk"], "left").select("host", "tk", "rest", "hits").mapInArrow(_cut, "host string, tk binary, text string")
    judged = opened.join(small.unionByName(counted), ["host", "tk"]).select("page_id", "url", "text")
    return settled.unionByName(judged).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
