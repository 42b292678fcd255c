"""HTML extraction by union-free regular expressions inferred from the pages of a host.

A page is read as a stream of block tags and text slots (inline markup belongs to the text it marks up). Streams of
one host are aligned one after another: a text mismatch becomes a slot, a block that only one side has becomes optional,
like neighbours are folded into a repeated group. The result, the host's wrapper, is an expression of
tags, slots, ``?`` and ``+`` without alternatives that matches every page of the host.

Main text is what lies in the page's article or main element and below no menu, header, footer, sidebar, notice, advert,
form or comment block. A page without such an element has its slots anywhere but in those blocks, less boilerplate:
slots that the wrapper saw constant over distinct pages (of several streams, or of one in which another slot varies). If
all of them are, as for copies of one page, they are its text.

Distribution: a task keeps one entry for each (host, stream) and says which slots vary; entries merge a (host,
stream), then streams of a host fold to its wrapper: a host with a third of all pages costs as much as its
few distinct streams. Wrappers are broadcast below a size limit, else joined by host.

Defined cases: null or empty html, or no main text, gives the empty text; a null or odd URL has the empty host; broken
nesting is repaired (a tag ends what it cannot contain); repeated rows are extracted each; an empty table gives an
empty table; extra columns are ignored; very long pages are read whole.
"""

from __future__ import annotations

import json
import re
import zlib
from html import unescape

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_LIMIT, staged, take_over

# Element names and the words of class and id attributes that mark what is not main text.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base col embed hr input link meta param source track".split())
HIDDEN = frozenset("head nav header footer aside form button select textarea option menu dialog iframe object canvas video audio map".split())
WORDS = frozenset(
    "ad ads advert adverts advertisement advertising banner promo promotion sponsor sponsored cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription "
    "sidebar menu nav navbar navigation breadcrumb breadcrumbs header masthead footer comment comments reply replies disqus share sharing social related recommended login signup search pagination pager toolbar widget copyright disclaimer".split()
)
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog form menu menubar".split())
MAIN = frozenset(["article", "main"])
CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
SCOPES = frozenset("ul ol dl table".split())

DROP = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?\]\]>|<(script|style|noscript|template|svg)\b[^>]*>.*?(?:</\1\s*>|$)|<[!?][^>]*>", re.S | re.I)
TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>")
MARKS = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
OFF = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)


def _noise(name: str, attrs: str) -> str:
    """``!`` for an element that holds no main text, ``@`` for the main element, else nothing."""
    if name in HIDDEN:
        return "!"
    if attrs:
        if OFF.search(attrs):
            return "!"
        for kind, *values in MARKS.findall(attrs):
            said = "".join(values)
            if kind.lower() == "role":
                if said.lower() in ROLES:
                    return "!"
                if said.lower() == "main":
                    return "@"
            elif name not in ("body", "html") and name not in MAIN and WORDS & set(re.split(r"[^a-z]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", said).lower())):
                return "!"
    return "@" if name in MAIN else ""


def _label(name: str, attrs: str) -> str:
    words = " ".join("".join(v) for k, *v in MARKS.findall(attrs) if k.lower() == "class") if attrs else ""
    return _noise(name, attrs) + name + ("." + ".".join(re.sub(r"\d+", "0", words).split()) if words else "")


def read(html: str | None, labels: dict[tuple[str, str], str]) -> tuple[str, list[str]]:
    """The page's stream (labels, ``/`` for an end, ``#`` for a text) and its texts. ``labels``: a cache."""
    if not html:
        return "", []
    parts = TAG.split(DROP.sub("", html))
    stream: list[str] = []
    texts: list[str] = []
    stack: list[str] = []
    text = parts[0]

    def close(at: int) -> None:
        nonlocal text
        flush()
        while len(stack) > at:
            stack.pop()
            stream.append("/")

    def flush() -> None:
        nonlocal text
        if text:
            if not text.isspace() and (stack or stream or text.strip()):
                stream.append("#")
                texts.append(text)
            text = ""

    def last(names, stop=frozenset()) -> int:
        for i in range(len(stack) - 1, -1, -1):
            if stack[i] in names:
                return i
            if stack[i] in stop:
                return -1
        return -1

    for i in range(1, len(parts), 4):
        slash, name, attrs, after = parts[i : i + 4]
        name = name.lower()
        if name in INLINE and not (attrs and not slash and "=" in attrs and name in ("span", "a", "small") and _noise(name, attrs)):
            if name == "br":
                text += " "
            text += after
            if slash and name in stack:  # an inline element that was opened as a block of its own
                tail = after
                text = text[: len(text) - len(after)]
                close(last((name,)))
                text = tail
            continue
        flush()
        if slash:
            if (at := last((name,))) >= 0:
                close(at)
        elif name not in VOID:
            if name in CLOSES_P and (at := last(("p",), SCOPES)) >= 0:
                close(at)
            if name in SAME and (at := last(SAME[name], SCOPES)) >= 0:
                close(at)
            if name in MAIN and not any(s in MAIN for s in stack):
                close(next((k + 1 for k, s in enumerate(stack) if s == "body"), 0 if "html" not in stack else stack.index("html") + 1))
            if name == "body" and "head" in stack:
                close(stack.index("head"))
            key = (name, attrs)
            if (label := labels.get(key)) is None:
                label = _label(name, attrs)
                if len(labels) < 20_000:
                    labels[key] = label
            if not attrs.endswith("/"):
                stack.append(name)
                stream.append(label)
        text = after
    close(0)
    return " ".join(stream), texts


# --- expressions: a node is [label, mark, children], a text slot ["#", mark, constant or None, distinct pages] ---

#: A slot names at most so many distinct pages that have it: as many make a constant boilerplate.
SEVERAL = 2


def tree_of(stream: str, constants: list[str | None], pages: tuple[int, ...] = ()) -> list:
    root: list = ["", "", []]
    stack, k = [root], 0
    for token in stream.split():
        if token == "/":
            stack.pop()
        elif token == "#":
            stack[-1][2].append(["#", "", constants[k], list(pages)])
            k += 1
        else:
            stack[-1][2].append([token, "", []])
            stack.append(stack[-1][2][-1])
    return root


def _mark(a: str, b: str) -> str:
    """The weaker of two marks: once, optional, repeated, optional and repeated."""
    return "*" if "*" in (a, b) or {a, b} == {"?", "+"} else a or b


def _common(a: list, b: list) -> list[tuple[int, int]]:
    """Places of a longest common subsequence of the labels."""
    if [x[0] for x in a] == [x[0] for x in b]:
        return [(i, i) for i in range(len(a))]
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i in range(len(a) - 1, -1, -1):
        for j in range(len(b) - 1, -1, -1):
            best[i][j] = best[i + 1][j + 1] + 1 if a[i][0] == b[j][0] else max(best[i + 1][j], best[i][j + 1])
    out, i, j = [], 0, 0
    while i < len(a) and j < len(b):
        if a[i][0] == b[j][0]:
            out.append((i, j))
            i, j = i + 1, j + 1
        elif best[i + 1][j] >= best[i][j + 1]:
            i += 1
        else:
            j += 1
    return out


def unify(a: list, b: list) -> list:
    """The least expression that covers both; labels agree."""
    if a[0] == "#":
        return ["#", _mark(a[1], b[1]), a[2] if a[2] == b[2] else None, sorted({*a[3], *b[3]})[:SEVERAL]]
    children, i, j = [], 0, 0
    optional = lambda x: [x[0], _mark(x[1], "?"), *x[2:]]
    for p, q in [*_common(a[2], b[2]), (len(a[2]), len(b[2]))]:
        children += [*map(optional, a[2][i:p]), *map(optional, b[2][j:q])]
        if p < len(a[2]):
            children.append(unify(a[2][p], b[2][q]))
        i, j = p + 1, q + 1
    return [a[0], _mark(a[1], b[1]), children]


def fold(x: list) -> list:
    """Like neighbours become one repeated group, from the leaves up."""
    if x[0] == "#":
        return x
    children: list = []
    for c in map(fold, x[2]):
        if children and children[-1][0] == c[0] != "#":
            both = unify(children[-1], c)
            children[-1] = [both[0], _mark(both[1], "+"), both[2]]
        else:
            children.append(c)
    return [x[0], x[1], children]


def infer(pages: list[tuple[str, list[str | None]]]) -> list:
    """The wrapper of streams with their constant texts (None: varies)."""
    whole = None
    for k, (stream, constants) in enumerate(pages):
        own = fold(tree_of(stream, constants, (2 * k, 2 * k + 1) if None in constants else (2 * k,)))
        whole = own if whole is None else fold(unify(whole, own))
    return whole


def expression(x: list) -> str:
    """The wrapper as a readable union-free regular expression."""
    if x[0] == "#":
        return ("#" if x[2] is None else json.dumps(x[2], ensure_ascii=False)) + x[1]
    inner = " ".join(map(expression, x[2]))
    body = f"<{x[0]}>{inner}</>" if x[0] else inner
    return f"({body}){x[1]}" if x[1] else body


def _has_main(x: list) -> bool:
    return x[0] != "#" and (x[0].startswith("@") or any(not c[0].startswith("!") and _has_main(c) for c in x[2]))


def main_slots(wrapper: list, stream: str) -> list[bool]:
    """For each text of a page's stream: does it fall into a main slot?"""
    page = tree_of(stream, [None] * stream.split().count("#"))
    inside, out, varying = _has_main(page), [], []

    def walk(node: list, slot: list | None, main: bool, off: bool) -> None:
        if node[0] == "#":
            out.append(not off and (main or not inside))
            varying.append(slot is None or slot[2] is None or len(slot[3]) < SEVERAL)
            return
        main, off = main or node[0].startswith("@"), off or node[0].startswith("!")
        children, slots = node[2], slot[2] if slot else []
        runs: list[list] = []  # like neighbours of the page share the slot of the repeated group
        for c in children:
            if runs and runs[-1][0] == c[0] != "#":
                runs[-1][1].append(c)
            else:
                runs.append([c[0], [c]])
        at = dict(_common(runs, slots))
        for k, (_, members) in enumerate(runs):
            for c in members:
                walk(c, slots[at[k]] if k in at else None, main, off)

    walk(page, wrapper, False, False)
    own = [o and v for o, v in zip(out, varying, strict=True)]
    return own if not inside and any(own) else out


def host_of(url) -> str:
    m = re.match(r".*?://([^/?#]*)", url or "", re.S)
    return m[1].lower() if m else ""


def _merge(old: list | None, new: list) -> list:
    return new if old is None else [a if a == b else None for a, b in zip(old, new, strict=True)]


def streams(pages: DataFrame) -> DataFrame:
    """(host, stream, constants, n): a row for each task, host and stream; constants hold the crc32 of texts that never varied."""

    def local(batches):
        import pyarrow as pa

        labels: dict = {}
        seen: dict = {}
        for b in batches:
            for url, html in zip(b.column("url").to_pylist(), b.column("html"), strict=True):
                stream, texts = read(html.as_py(), labels)
                key = (host_of(url), stream)
                old = seen.get(key)
                marks = [None if old and old[0][k] is None else str(zlib.crc32(t.encode("utf-8", "replace"))) for k, t in enumerate(texts)]
                seen[key] = (_merge(old and old[0], marks), (old[1] if old else 0) + 1)
        rows = [(h, s, json.dumps(c), n) for (h, s), (c, n) in seen.items()]
        for i in range(0, len(rows), 1000):
            cols = zip(*rows[i : i + 1000], strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.string(), pa.string(), pa.int64()), strict=True)], names=["host", "stream", "constants", "n"])

    return pages.select("url", "html").mapInArrow(local, "host string, stream string, constants string, n long")


def wrappers(pages: DataFrame) -> DataFrame:
    """(host, wrapper as JSON, n_pages): one row a host."""

    def merged(pdf):
        out = None
        for c in pdf["constants"]:
            out = _merge(out, json.loads(c))
        return pdf.iloc[:1].assign(constants=json.dumps(out), n=int(pdf["n"].sum()))

    def folded(pdf):
        import pandas as pd

        pdf = pdf.sort_values("stream")
        wrapper = infer([(s, json.loads(c)) for s, c in zip(pdf["stream"], pdf["constants"], strict=True)])
        return pd.DataFrame({"host": [pdf["host"].iloc[0]], "wrapper": [json.dumps(wrapper)], "n_pages": [int(pdf["n"].sum())]})

    schema = "host string, stream string, constants string, n long"
    once = streams(pages).groupBy("host", "stream").applyInPandas(merged, schema)
    return once.groupBy("host").applyInPandas(folded, "host string, wrapper string, n_pages long")


def clean(text: str) -> str:
    return " ".join(unescape(text).split())


def extract(pages: DataFrame, limit: int = BROADCAST_LIMIT, keep: tuple[str, ...] = ()) -> DataFrame:
    """page_id, url, the columns of ``keep``, text and n_chars of every page."""
    learnt = staged(wrappers(pages), "wrappers")
    size = learnt.agg(F.sum(F.length("wrapper") + F.length("host") + 64)).first()[0] or 0
    table = None
    rows = pages.select("page_id", "url", "html", *keep)
    if size <= limit:
        table = pages.sparkSession.sparkContext.broadcast({r["host"]: r["wrapper"] for r in learnt.toLocalIterator()})
    else:
        shape = r"(?s)^.*?://([^/?#]*)"
        rows = rows.withColumn("host", F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), shape, 1))).join(learnt, "host", "left").select("page_id", "url", "html", *keep, "wrapper")
    names = rows.columns

    def pull(batches):
        import pyarrow as pa

        take_over("pages")
        labels: dict = {}
        slots: dict = {}
        held: dict = {}
        for b in batches:
            texts = []
            given = iter(b.column("wrapper").to_pylist()) if "wrapper" in names else None
            for url, html in zip(b.column("url").to_pylist(), b.column("html"), strict=True):
                stream, parts = read(html.as_py(), labels)
                host = host_of(url)
                packed = next(given) if given else table.value.get(host)
                if (main := slots.get((host, stream))) is None:
                    if host not in held:
                        held[host] = json.loads(packed)
                    main = slots[host, stream] = main_slots(held[host], stream)
                    if len(slots) > 50_000:
                        slots.clear()
                        held.clear()
                texts.append("\n".join(t for p, keep in zip(parts, main, strict=True) if keep and (t := clean(p))))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in carried), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*carried, "text", "n_chars"])

    kinds, carried = dict(pages.dtypes), ("page_id", "url", *keep)
    return rows.mapInArrow(pull, ", ".join([*(f"`{c}` {kinds[c]}" for c in carried), "text string", "n_chars long"]))


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
