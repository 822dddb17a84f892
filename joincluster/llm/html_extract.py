"""Main text of web pages by template deduction over equivalence classes.

A page is a sequence of tokens: tags told apart by their path and roles, and text blocks. The
occurrence vector of a token is its count on each different page of the host that is not empty.
Tokens of equal vectors form a class, whatever the counts and however few pages (LEAST_PAGES at
least) hold it. A class is in order if its tokens come on each of its pages as one period, repeated;
two classes nest if no token of one stands between the first and last of the other's period while
its own period is open. A class that is out of order, or crosses one that has
more pages or tokens, is taken apart into single tokens. Text that only shares a vector with text, on at most half of a
host's pages, is not told from a passage that several articles quote, so it stays data.

Text blocks of the template are its own words. What lies between template tokens are slots, named
by the innermost open class and the place in its period; a slot's role is read from the template
tags around it, and the data of the article's slots is the result.

Vectors are compared as two sums of 32-bit hashes over pages and the counts, so they are built by a
plain group-by; no page of a host meets another in a task.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as c
from .urlfilter import split_url

#: A class is a template's only from so many different pages on.
LEAST_PAGES = 4
#: Template tokens of this many bytes at most are broadcast; beyond it they are joined by host.
BROADCAST_MOST = 32 << 20
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>"
    r"|<(?P<raw>script|style|textarea|select|option|iframe|object|svg|math|template|noscript|title|button|canvas|audio|video)\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*>(?:.*?</(?P=raw)\s*>|.*\Z)"
    r"|<(?P<close>/)?(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>"
    r"|(?P<text>[^<]+|<)",
    re.S | re.I,
)
_ATTR = re.compile(r"(?:class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
# Element names and role words.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
SIDE_TAGS = frozenset("nav aside footer form menu dialog fieldset head".split())
SIDE_WORDS = frozenset(
    "ad ads advert advertisement advertisements adverts banner breadcrumb breadcrumbs comment comments commentlist complementary consent contentinfo cookie cookies "
    "disqus footer form header login masthead menu modal nav navbar navigation newsletter notice notices pagination popup promo promoted promotion related "
    "replies respond search share sharing sidebar signup social sponsor sponsored subscribe toolbar widget".split()
)


#: Elements of running text: there a name says only with all of its words what an element is.
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption table tr td th ul ol li dl dt dd".split())


def _role(tag: str, attrs: str, inside: bool) -> str:
    """main, side or empty. Inside an article a paragraph of class notice-of-meeting is its text, one of class cookie-notice is not."""
    names = [w for m in _ATTR.finditer(attrs) for w in (m[1] or m[2] or m[3] or "").lower().split()] if attrs else []
    parts = [[x for x in re.split(r"[^a-z0-9]+", w) if x] for w in names]
    words = {x for w in parts for x in w}
    named = any(w and SIDE_WORDS.issuperset(w) for w in parts) if inside and tag in PROSE else bool(words & SIDE_WORDS)
    if tag in SIDE_TAGS or named and tag not in ("html", "body", "article", "main") or tag == "header" and not inside:
        return "side"
    return "main" if tag in ("article", "main") or "main" in words and tag == "div" else ""


def _path(stack: list[tuple[str, str]]) -> str:
    return "/".join(f"{t}:{r}" if r else t for t, r in stack)


def blocks(html: str) -> list[tuple[str, str]]:
    """(role, text) of the text blocks of a page in order, and (name, '') of its tags told apart by path and roles; role is main, body or side."""
    out: list[tuple[str, str]] = []
    stack: list[tuple[str, str]] = []
    text: list[str] = []

    def role() -> str:
        roles = [r for _, r in stack]
        return "side" if "side" in roles else "main" if "main" in roles else "body"

    def end() -> None:
        if text:
            if words := " ".join(unescape("".join(text)).split()):
                out.append((role(), words))
            text.clear()

    for m in _TOKEN.finditer(html):
        if m["text"]:
            text.append(m["text"])
            continue
        tag = (m["tag"] or "").lower()
        if not tag:
            continue
        if tag == "br":
            text.append(" ")
        if tag in INLINE and not (tag == "span" and m["attrs"] and _role(tag, m["attrs"], True) == "side") and not (m["close"] and any(t == tag for t, _ in stack)):
            continue
        end()
        if m["close"]:
            at = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), -1)
            if at >= 0:
                # A paragraph left open must not swallow the end of what encloses it.
                del stack[at:]
            out.append((f"</{tag}>{_path(stack)}", ""))
        elif tag not in VOID:
            if tag in ("p", "li", "dt", "dd", "option", "tr", "td", "th") or stack and stack[-1][0] == "p":
                closes = {"li": ("li", "p"), "tr": ("tr", "td", "th", "p"), "td": ("td", "th", "p"), "th": ("td", "th", "p"), "dt": ("dt", "dd", "p"), "dd": ("dt", "dd", "p")}.get(tag, ("p",))
                while stack and stack[-1][0] in closes:
                    stack.pop()
            stack.append((tag, _role(tag, m["attrs"], any(r == "main" for _, r in stack))))
            out.append((f"<{_path(stack)}>", ""))
    end()
    return out


def _hash(s: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(s.encode("utf-8", "surrogatepass")) - (1 << 63)


def tokens(html: str | None) -> list[tuple[int, str, str]]:
    """(hash, role or tag name, text) of a page's tokens; a tag's hash is odd and has no text, a text block's is even."""
    return [(_hash("t" + t) & ~1 if t else _hash("g" + n) | 1, n, t) for n, t in blocks(html or "")]


def _counts(pages: DataFrame) -> DataFrame:
    """host, token, page, n: how often each token stands on each different page; token 0 stands once on every page that is not empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            held: set[tuple[str, int]] = set()
            rows: list[tuple[str, int, int, int]] = []
            for host, page, html in zip(b.column("host").to_pylist(), b.column("page").to_pylist(), b.column("html").to_pylist(), strict=True):
                if not host or (host, page) in held:
                    continue
                held.add((host, page))
                seen = Counter(k for k, _, _ in tokens(html))
                if seen:
                    rows.append((host, 0, page, 1))
                    rows += [(host, k, page, n) for k, n in seen.items()]
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
            kinds = [pa.string(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(cols, kinds, strict=True)], ["host", "token", "page", "n"])

    return pages.mapInArrow(run, "host string, token long, page long, n long")


def classes(pages: DataFrame) -> DataFrame:
    """host, all, classes: how many different pages a host has, and its equivalence classes (pages, tokens), those of more pages, then tokens, first."""
    mix = F.xxhash64("page", "n")
    sums = c.written(
        _counts(pages).distinct().groupBy("host", "token")
        .agg(F.count("*").alias("pages"), F.sum("n").alias("total"), F.sum(mix.bitwiseAND(F.lit(0xFFFFFFFF))).alias("v1"), F.sum(F.shiftrightunsigned(mix, 32)).alias("v2"))
        .where(f"pages >= {LEAST_PAGES}")
    )
    whole = sums.where("token = 0").select("host", F.col("pages").alias("all"))
    same = sums.where("token != 0").groupBy("host", "pages", "total", "v1", "v2").agg(F.array_sort(F.collect_list("token")).alias("tokens")).join(whole, "host")
    # A tag's token is odd.
    same = same.where((F.col("pages") * 2 > F.col("all")) | F.exists("tokens", lambda t: t.bitwiseAND(F.lit(1)) == 1))
    one = F.struct((-F.col("pages")).alias("less"), (-F.size("tokens")).alias("size"), "tokens")
    return same.groupBy("host", "all").agg(F.transform(F.array_sort(F.collect_list(one)), lambda x: F.struct((-x["less"]).alias("pages"), x["tokens"].alias("tokens"))).alias("classes"))


def _walk(seq: list[tuple[int, int]], sizes: dict[int, int]) -> set[tuple[int, int]]:
    """The pairs of classes (smaller number first) that cross in seq, the (place, class) of a page's tokens in order."""
    at = dict.fromkeys(sizes, 0)
    opened: dict[int, int] = {}
    last: dict[int, int] = {}
    crossing = set()
    for place, k in seq:
        if at[k]:
            crossing |= {(min(k, o), max(k, o)) for o, p in opened.items() if o != k and p > last[k]}
        else:
            opened[k] = place
        last[k] = place
        at[k] = (at[k] + 1) % sizes[k]
        if not at[k]:
            del opened[k]
    return crossing


def faults(html: str | None, held: list[list[int]]) -> tuple[dict[int, int], set[tuple[int, int]]]:
    """Of a page and its host's classes: for each class on it the hash of its order (0 if it is not one period, repeated), and the pairs of classes that cross."""
    of = {t: k for k, ts in enumerate(held) for t in ts}
    seq = [(i, of[t], t) for i, (t, _, _) in enumerate(tokens(html)) if t in of]
    own: dict[int, list[int]] = defaultdict(list)
    for _, k, t in seq:
        own[k].append(t)
    orders = {}
    for k, ts in own.items():
        m = len(held[k])
        good = len(ts) % m == 0 and set(ts[:m]) == set(held[k]) and ts == ts[:m] * (len(ts) // m)
        orders[k] = (_hash(",".join(map(str, ts[:m]))) or 1) if good else 0
    fit = {k: len(held[k]) for k, h in orders.items() if h}
    return orders, _walk([(i, k) for i, k, _ in seq if k in fit], fit)


def _checked(joined: DataFrame) -> DataFrame:
    """host, bad, crossing: numbers of the classes that are not in one order on all their pages, and pairs that cross on some page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: set[tuple[str, int, int, int]] = set()
            held: dict[str, list[list[int]]] = {}
            for i, (host, html) in enumerate(zip(b.column("host").to_pylist(), b.column("html").to_pylist(), strict=True)):
                if host not in held:
                    held[host] = [x["tokens"] for x in b.column("classes")[i].as_py() or ()]
                if held[host]:
                    orders, crossing = faults(html, held[host])
                    rows |= {(host, k, -1, h) for k, h in orders.items()} | {(host, a, o, 0) for a, o in crossing}
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
            kinds = [pa.string(), pa.int32(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(cols, kinds, strict=True)], ["host", "a", "b", "order"])

    seen = joined.select("host", "html", "classes").mapInArrow(run, "host string, a int, b int, order long").groupBy("host", "a", "b").agg(F.min("order").alias("low"), F.max("order").alias("high"))
    bad = F.collect_list(F.when((F.col("b") < 0) & ((F.col("low") != F.col("high")) | (F.col("low") == 0)), F.col("a")))
    return seen.groupBy("host").agg(bad.alias("bad"), F.collect_list(F.when(F.col("b") >= 0, F.struct("a", "b"))).alias("crossing"))


def _joined(read: DataFrame, found: DataFrame) -> DataFrame:
    """read with the columns of found by host; a small table is broadcast, else each host's row goes to all of its salts."""
    size = found.agg(F.sum(F.aggregate("classes", F.lit(0), lambda a, x: a + F.size(x["tokens"]) * 8 + 16) + F.length("host") + 16)).first()[0] or 0
    if size <= BROADCAST_MOST:
        return read.join(F.broadcast(found), "host", "left")
    salts = 64
    return read.withColumn("salt", F.pmod("page", F.lit(salts))).join(found.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).cast("long")), ["host", "salt"], "left").drop("salt")


def templates(read: DataFrame) -> DataFrame:
    """host, all, classes, bad, crossing of the hosts that have a template; read has host, page and html."""
    found = c.written(classes(read.select("host", "page", "html")))
    return c.written(found.join(_checked(_joined(read.select("host", "page", "html"), found).where("classes is not null")), "host", "left"))


@dataclass
class Template:
    """of: the class of each token; sizes: how many tokens each class has. The classes nest."""

    of: dict[int, int] = field(default_factory=dict)
    sizes: dict[int, int] = field(default_factory=dict)

    @classmethod
    def read(cls, pages: int, found: list[dict], bad: list[int], crossing: list[dict]) -> Template:
        out, loose = cls(), set(bad)
        against = defaultdict(set)
        for x in crossing:
            against[x["b"]].add(x["a"])
        for k, x in enumerate(found):
            if k in loose or any(o not in loose for o in against[k]):
                loose.add(k)
                parts = [[t] for t in x["tokens"] if t & 1 or x["pages"] * 2 > pages]
            else:
                parts = [x["tokens"]]
            for ts in parts:
                out.of |= dict.fromkeys(ts, len(out.sizes))
                out.sizes[len(out.sizes)] = len(ts)
        return out


def slots(html: str | None, template: Template | None) -> list[tuple[tuple[tuple[int, int], ...], str, str]]:
    """(slot, role, text) of a page's data in order: a slot is the open classes from the outside in, each with how many tokens of its period have passed.

    Without a template the page is one slot, and its tags give the roles.
    """
    template = template or Template()
    at: dict[int, int] = {}
    out = []
    for t, role, text in tokens(html):
        k = template.of.get(t)
        if k is None:
            if text:
                out.append((tuple(at.items()), role, text))
        elif template.sizes[k] > 1:
            at[k] = at.get(k, 0) + 1
            if at[k] == template.sizes[k]:
                del at[k]
    return out


def article(html: str | None, template: Template | None) -> str:
    """The data of the article's slots, one block a line; on a page without a slot of that role, the data of all slots but the side ones."""
    found = slots(html, template)
    main = [t for _, r, t in found if r == "main"]
    return "\n".join(main or [t for _, r, t in found if r == "body"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for every row of pages.

    A null or empty html, and a page without an article, has the empty text; a page without a host
    has no template. Rows that repeat are extracted each for itself. An empty table gives an empty
    result.
    """
    host, _ = split_url(F.col("url"))
    read = pages.select("page_id", "url", "html").select("page_id", "url", host.alias("host"), F.xxhash64(F.coalesce("html", F.lit(""))).alias("page"), "html")
    joined = _joined(read, templates(read))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                b = batch.slice(lo, 1000)
                held: dict[str, Template | None] = {None: None}
                texts = []
                for i, (host, html) in enumerate(zip(b.column("host").to_pylist(), b.column("html").to_pylist(), strict=True)):
                    if host not in held:
                        found = b.column("classes")[i].as_py()
                        held[host] = Template.read(b.column("all")[i].as_py(), found, b.column("bad")[i].as_py() or [], b.column("crossing")[i].as_py() or []) if found else None
                    texts.append(article(html, held[host]))
                yield pa.RecordBatch.from_arrays([b.column("page_id").cast(pa.int64()), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return joined.select("page_id", "url", "host", "html", "all", "classes", "bad", "crossing").mapInArrow(run, "page_id long, url string, text string, n_chars long")
