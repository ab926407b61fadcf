"""Main text of web pages by consensus host paths.

Every page is read into blocks of text and containers, each a run of blocks with a path of generalised tags and
classes (digits dropped). A path is named by a rolling hash of the paths above it and its own last step, so that deep pages cost no more.
An element whose name marks it as no article is left out whole, unless it holds an article or main element or its name also says
content, and it holds most of the page's text: such names (with-sidebar, search-page) tell of the page around. A container's score is the share of the page's plain text that it holds, times the share of
its own text that is plain (neither a link nor part of a menu, footer, advert and the like), raised where its name
says article or content. Every page votes for its best path with its score (one vote, since
the containers around the best one hold its text too and would outvote it where articles are long), Spark adds the votes up per host, and each page is read again
with the path that its host agrees on; a page that lacks it uses its own best container.

White space inside a block becomes one space, blocks are trimmed and joined by \\n in page order, character references
are decoded. Null or empty html gives an empty text, and so does a page without plain text; a null url belongs to the
host "". Repeated rows are extracted each alike; extra columns are left out but for `columns`; an empty table gives an empty
result. Pages of any length are read whole. Votes are whole numbers, so results do not depend on their order; the
winners' table is broadcast only if it is counted to be small.
"""

from __future__ import annotations

import html as _html
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, lower_az, short_batches, small

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+|[^>]*)>|<[!?][^>]*>", re.S)
ATTRIBUTE = re.compile(r"([a-zA-Z:-]+)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
# What HTML calls these elements.
RAW = frozenset(("script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"))
VOID = frozenset(("br", "hr", "img", "input", "meta", "link", "wbr", "col", "area", "base", "embed", "source", "track", "param"))
INLINE = frozenset((
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "rp", "rt", "ruby",
    "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var",
))
NEVER = frozenset((
    "nav", "footer", "aside", "form", "noscript", "template", "svg", "math", "object", "button", "select", "option", "head", "dialog", "menu", "canvas", "audio", "video", "applet",
))
ONCE = {"p": ("p",), "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
HOLDS = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",)}
CONTAINERS = frozenset(("body", "main", "article", "section", "div", "td", "center", "blockquote", "figure", "table", "tbody"))
#: Words in a class, id or role that mark what is not the article.
ASIDE = frozenset((
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "adsense", "banner", "sponsor", "sponsored", "promo", "promotion", "nav", "navbar", "navigation",
    "menu", "menubar", "breadcrumb", "breadcrumbs", "sidebar", "footer", "cookie", "cookies", "consent", "gdpr", "notice", "popup", "modal", "overlay", "newsletter",
    "subscribe", "subscription", "signup", "login", "comment", "comments", "commentlist", "disqus", "replies", "respond", "social", "share", "sharing", "related",
    "recommended", "recommendations", "widget", "pagination", "pager", "toolbar", "masthead", "copyright", "skip", "contentinfo", "complementary", "search", "dialog", "alert",
))
REMARKS = frozenset(("comment", "comments", "reply", "replies"))
GOOD = frozenset(("article", "content", "post", "entry", "story", "main", "text", "body"))
VOTES_OF_A_PAGE = 1
#: A container with this share of a page's plain text has enough: a wider one around it scores no more, and the deeper wins.
ENOUGH = 0.9


def _words(value: str) -> list[str]:
    return [w.lower() for w in re.split(r"[^A-Za-z]+|(?<=[a-z])(?=[A-Z])", value) if w]


def _step(above: str, step: str) -> str:
    """Name of a path: a hash of all of it, and its last step."""
    return f"{xxhash.xxh3_64_hexdigest(above + '>' + step)}>{step}"


class _Open:
    """An element that is open: name, whether it is left out (1), and only by its name (2), its path, first block and words."""

    __slots__ = ("name", "out", "path", "start", "words", "nested", "before", "holds")

    def __init__(self, name, out, path, start, words, nested=0, before=None):
        self.name, self.out, self.path, self.start, self.words, self.nested, self.before, self.holds = name, out, path, start, words, nested, before, False


class Page:
    """Blocks of a page: their texts, plain and linked lengths; and its containers (path, first block, end, depth, words of the name)."""

    def __init__(self, source: str):
        self.texts: list[str] = []
        self.plain: list[int] = []
        self.other: list[int] = []
        self.containers: list[tuple[str, int, int, int, frozenset]] = []
        self._doubtful: list[tuple[int, int, bool, frozenset]] = []
        self._read(source)
        self._leave_out()

    def _flush(self) -> None:
        if self._buffer:
            text = " ".join(_html.unescape("".join(self._buffer)).split())
            if text:
                out = self._out > 0
                link = min(self._link_chars, len(text))
                self.texts.append("" if out else text)
                self.plain.append(0 if out else len(text) - link)
                self.other.append(len(text) if out else link)
            self._buffer.clear()
        self._link_chars = 0

    def _leave_out(self) -> None:
        """Elements out by their name alone: from the outermost on, each goes unless it is the page's content after all."""
        if not self._doubtful:
            return
        before = np.concatenate([[0], np.cumsum(self.plain)])
        done = 0
        for start, end, holds, words in sorted(self._doubtful, key=lambda d: (d[0], -d[1])):
            if end <= done:
                continue
            if (holds or words & GOOD) and not words & REMARKS and 2 * (before[end] - before[start]) > before[-1]:
                continue
            for i in range(max(start, done), end):
                self.other[i] += self.plain[i]
                self.plain[i], self.texts[i] = 0, ""
            done = end

    def _pop(self) -> None:
        self._flush()
        held = self._stack.pop()
        self._count[held.name] -= 1
        if held.before is not None:  # an inline element left out: the block around it goes on
            self._out -= 1
            self._buffer, self._link_chars = [*held.before[0], " "], held.before[1]
            return
        if held.name in ("article", "main"):
            self._inside -= 1
        hard = held.out == 1
        if self._stack and (held.holds or (held.name in ("article", "main") and not held.out)):
            self._stack[-1].holds = True
        if held.out == 2:
            self._doubtful.append((held.start, len(self.texts), held.holds, held.words))
        if held.name in CONTAINERS and not hard and self._out == 0:
            self.containers.append((held.path, held.start, len(self.texts), len(self._stack), held.words))
        self._out -= hard

    def _text(self, text: str) -> None:
        if text:
            self._buffer.append(text)
            if self._link:
                self._link_chars += len(text.strip())

    def _read(self, source: str) -> None:
        self._buffer: list[str] = []
        self._stack: list[_Open] = []
        self._count: dict[str, int] = {}
        self._out = self._link = self._link_chars = self._inside = 0
        at, search = 0, TAG.search
        while m := search(source, at):
            self._text(source[at : m.start()])
            at = m.end()
            if not m[2]:
                continue
            name = m[2].lower()
            if m[1]:
                self._close(name)
                continue
            self._open(name, m[3])
            if name in RAW and not m[3].endswith("/"):
                end = re.compile(rf"</{name}\s*[^>]*>|\Z", re.I).search(source, at)
                at = end.end()
        self._text(source[at:])
        self._flush()
        while self._stack:
            self._pop()

    def _push(self, held: _Open) -> None:
        self._stack.append(held)
        self._count[held.name] = self._count.get(held.name, 0) + 1

    def _open(self, name: str, attributes: str) -> None:
        if name in VOID:
            if name == "br":
                self._buffer.append(" ")
            elif name == "hr":
                self._flush()
            return
        if name in RAW:
            return
        if name in INLINE:
            if name == "a":
                self._link = 1
            if self._stack and self._stack[-1].name == name and self._stack[-1].nested:
                self._stack[-1].nested += 1  # inside an inline element that is left out: its own kind nests
            elif attributes and self._aside(name, attributes)[0]:
                before, self._buffer = (self._buffer, self._link_chars), []
                self._push(_Open(name, 1, "", len(self.texts), frozenset(), 1, before))
                self._out += 1
            return
        self._flush()
        self._link = 0
        for closed in ONCE.get(name, ("p",) if name not in ("html", "body") else ()):
            self._close_open(closed, HOLDS.get(name, ()) if closed != "p" else ())
        out, classes, named = self._aside(name, attributes)
        above = next((s.path for s in reversed(self._stack) if s.path), "")
        self._push(_Open(name, out, _step(above, name + "".join(f".{w}" for w in sorted(classes))), len(self.texts), named if out == 2 else classes))
        self._inside += name in ("article", "main")
        self._out += out == 1

    def _close_open(self, name: str, until: tuple[str, ...]) -> None:
        """Close an element that ends by itself where the next begins, if it is open inside the innermost of `until`."""
        if not self._count.get(name):
            return
        for i in range(len(self._stack) - 1, -1, -1):
            held = self._stack[i].name
            if held == name:
                while len(self._stack) > i:
                    self._pop()
                return
            if held in until or (not until and held not in INLINE):
                return

    def _close(self, name: str) -> None:
        if name in VOID:
            if name == "br":
                self._buffer.append(" ")
            return
        if name in INLINE:
            if name == "a":
                self._link = 0
            if self._stack and self._stack[-1].name == name and self._stack[-1].nested:
                self._stack[-1].nested -= 1
                if not self._stack[-1].nested:
                    self._pop()
            return
        self._flush()
        self._link = 0
        if self._count.get(name):
            while self._stack[-1].name != name:
                self._pop()
            self._pop()

    def _aside(self, name: str, attributes: str) -> tuple[int, frozenset, frozenset]:
        """Whether an element is left out (1) or may be, by its name alone (2); the words of its classes; those of all its names."""
        found = {}
        if attributes and not attributes.isspace():
            for k, *v in ATTRIBUTE.findall(attributes):
                found.setdefault(k.lower(), v[0] or v[1] or v[2])
        classes = frozenset(_words(found.get("class", "")))
        named = classes | set(_words(found.get("id", "") + " " + found.get("role", "")))
        if name in ("html", "body", "main"):
            return 0, classes, named
        if name == "article":
            return int(bool(named & REMARKS)), classes, named
        hidden = "hidden" in found or found.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", found.get("style", ""), re.I) is not None
        if name in NEVER or hidden or (not self._inside and (name == "header" or "header" in named)):
            return 1, classes, named
        return 2 * bool(named & ASIDE), classes, named

    def scores(self) -> list[int]:
        """Score of each container, in thousandths."""
        plain, other = (np.concatenate([[0], np.cumsum(x)]) for x in (self.plain, self.other))
        out = []
        for _, start, end, depth, words in self.containers:
            mine, rest = plain[end] - plain[start], other[end] - other[start]
            raised = 1.25 if words & GOOD else 1.0
            held = min(1.0, mine / max(1, plain[-1]) / ENOUGH)
            out.append(int(1000 * raised * held * mine / max(1, mine + rest)) + min(depth, 9) if mine else 0)
        for i, (path, *_) in enumerate(self.containers):
            if out[i] and path.rpartition(">")[2].split(".")[0] in ("article", "main"):
                out[i] = int(out[i] * 1.25)
        return out

    def best(self) -> list[tuple[str, int]]:
        """The page's best paths with their scores: several containers of one path count together."""
        total: dict[str, int] = {}
        for (path, *_), s in zip(self.containers, self.scores(), strict=True):
            total[path] = total.get(path, 0) + s
        return sorted(((p, s) for p, s in total.items() if s), key=lambda x: (-x[1], x[0]))[:VOTES_OF_A_PAGE]

    def text(self, path: str | None) -> str:
        """Texts of the containers of this path, or of the page's best one, or of all blocks if there is none."""
        spans = [(s, e) for p, s, e, _, _ in self.containers if p == path and any(self.texts[s:e])]
        if not spans:
            scored = [(s, -i) for i, s in enumerate(self.scores()) if s]
            spans = [self.containers[-max(scored)[1]][1:3]] if scored else [(0, len(self.texts))]
        out, done = [], 0
        for s, e in sorted(spans, key=lambda x: (x[0], -x[1])):
            out += self.texts[max(s, done) : e]
            done = max(done, e)
        return "\n".join(t for t in out if t)


def _votes(batches):
    for b in batches:
        hosts, paths, scores = [], [], []
        for h, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            if source := t.as_py():
                for p, s in Page(source).best():
                    hosts.append(h)
                    paths.append(p)
                    scores.append(s)
        yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(paths, pa.string()), pa.array(scores, pa.int64())], ["host", "path", "score"])


def _texts(n: int):
    def run(batches):
        for b in batches:
            out = [Page(t.as_py()).text(p) if t.is_valid else "" for p, t in zip(b.column(n).to_pylist(), b.column(n + 1), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(out, pa.string())], [*b.schema.names[:n], "text"])

    return run


def host(url):
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), "^[\\s\\S]*?://([^/?#]*)", 1)
    return lower_az(rest)


def host_paths(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(host, path): the path with the most votes of each host."""
    votes = pages.select(host(F.col(url)).alias("host"), F.col(html).alias("html")).mapInArrow(_votes, "host string, path string, score long")
    sums = votes.groupBy("host", "path").agg(F.sum("score").alias("s"))
    return sums.groupBy("host").agg(F.max_by("path", F.struct("s", "path")).alias("path"))


def extract(pages: DataFrame, url: str = "url", html: str = "html", columns: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """columns, text and n_chars of every page."""
    short_batches(pages.sparkSession)
    winners = keep(host_paths(pages, url, html)).select(F.col("host").alias("__host"), F.col("path").alias("__path"))
    rows = pages.select(*columns, host(F.col(url)).alias("__h"), F.col(html).alias("__html"))
    rows = rows.join(small(winners), F.col("__h") == F.col("__host"), "left").select(*columns, "__path", "__html")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-2])
    out = rows.mapInArrow(_texts(len(columns)), f"{schema}, text string")
    return out.withColumn("n_chars", F.length("text").cast("long"))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return extract(table(spark, sf_dir, "pages"))
