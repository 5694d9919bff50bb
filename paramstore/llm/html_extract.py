"""Main text of web pages by equivalence classes of template tokens.

Tokens of a page are its opening and closing tags and its text lines, each within its path of elements (so that one tag in two roles is
two tokens). Spark sums, for each host and token, a signature of the token's occurrence vector: over the host's pages, a hash of page
and count. Tokens of one host with the same signature, support and total have the same occurrence vector and form an equivalence class.
A class is kept if it is large (`least_size` tokens) and frequent (`least_share` of the host's pages, three pages at least). Valid classes
nest: their tokens are ordered by mean place, and a class that is interleaved with the tokens of a larger one, neither before, after
nor within one of its gaps, is dropped. What is left is the host's template. Hosts of fewer than three pages have one template together.

The template's tokens part the rest of a page into slots, and the slots that hold the main text are found over the host's pages, not
page by page: for every element of the template, the text of the slots within it that is neither link nor a named boilerplate
element's is summed. Sections that hold `least_mass` of the text of the pages that have them lie within each other; the innermost one
is the host's container, the next ones stand in for it on pages without it. A page's text is the slots of its container. Only within
the container do names decide: elements named as boilerplate (menus, notices, adverts, forms, comments, scripts, styles) are left out.
Text lines of the template are no slots; within a container below the body they count as slots, so that an article which many pages of
a host copy is not taken for a template. A page whose template has no container, for want of pages, goes by the names of elements alone.
Character references are decoded, white space within a block becomes one space, blocks are joined in page order by one space.

A host is never gathered: signatures and text masses are sums, and a template is at most the tokens of about two pages. Templates are
measured and broadcast up to `most_bytes`; beyond, pages meet theirs by a join whose hot hosts Spark may split. Nulls: null html is
empty html with empty text; a null url is a host of its own. Rows are kept one for one. Empty tables give empty results.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from paramstore.llm.common import cut, per_batch

MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][\w:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.DOTALL)
CLASSES = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.IGNORECASE)

#: Elements of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template svg math xmp".split())
BLOCK = frozenset("address article aside blockquote body br center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main nav ol option p pre section select table tbody td tfoot th thead title tr ul".split())
BOILER_TAGS = frozenset("head script style textarea title noscript iframe template svg math nav footer aside form button select option label input dialog menu object canvas audio video".split())
CLOSES_P = BLOCK - {"br", "option", "head", "html", "body"}

#: Words of class, id and role attributes that mark boilerplate, and that mark the article.
BOILER = re.compile(r"(?:^|[\s_-])(?:nav\w*|menu\w*|header|masthead|banner|foot(?:er)?|side-?bar\w*|aside|complementary|contentinfo|navigation|notices?|alerts?|cookies?|consent|gdpr|popup|modal|overlay|newsletter|subscri\w+|sign-?up|login|ads?|adverts?|advertis\w+|sponsor\w*|promo\w*|form|search\w*|comments?|comment-?list|replies|respond|disqus|discussion|related|recommend\w*|share|sharing|social|breadcrumbs?|pagination|pager|widget\w*|toolbar|skip\w*|hidden|copyright|legal|disclaimer)(?:$|[\s_-])", re.IGNORECASE)
ARTICLE_TAGS = frozenset(("article", "main"))
#: Sections: elements that may be the container of a page's main text.
SECTION = frozenset("article body center details div fieldset form html main section table tbody td tr".split())
#: An article element of these classes is a reader's comment or a link to another article.
OTHER_ARTICLE = re.compile(r"comment|repl(?:y|ies)|respon[ds]|related|recommend|teaser|promo", re.IGNORECASE)


HALF = 1 << 63
TAG, END, TEXT, BREAK = range(4)


class Token(NamedTuple):
    """kind; node: the hash of the path of the element (the innermost one around a text); value: a text, or an element's name; depth: elements around it."""

    kind: int
    node: int
    value: str
    boiler: bool
    article: bool
    link: bool
    depth: int


def parse(text: str) -> Iterator[Token]:
    """The tokens of a page; BREAK where a block begins or ends."""
    stack: list[tuple[str, int, bool, bool, bool]] = []
    is_open: Counter[str] = Counter()
    at, size = 0, len(text)
    outside = (0, False, False, False)
    node, boiler, article, link = outside
    while at < size:
        m = MARKUP.search(text, at)
        start = m.start() if m else size
        if start > at:
            yield Token(TEXT, node, text[at:start], boiler, article, link, len(stack))
        if not m:
            break
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA["):
                yield Token(TEXT, node, entities.escape(m[0][9:].removesuffix("]]>")), boiler, article, link, len(stack))
            continue
        name = m[2].lower()
        if name in BLOCK:
            yield Token(BREAK, node, name, boiler, article, link, len(stack))
        if m[1]:
            for depth in range(len(stack) - 1 if is_open[name] else -1, -1, -1):
                if stack[depth][0] == name:
                    yield Token(END, stack[depth][1], name, boiler, article, link, depth)
                    is_open.subtract(x[0] for x in stack[depth:])
                    del stack[depth:]
                    break
                if stack[depth][0] in ("article", "main", "body", "table") and name in ("p", "b", "i", "em", "strong", "a", "span", "li"):
                    break
            node, boiler, article, link = stack[-1][1:] if stack else outside
            continue
        if name in CLOSES_P and any(x[0] == "p" for x in stack[-4:]):
            while stack[-1][0] != "p":
                is_open[stack.pop()[0]] -= 1
            is_open[stack.pop()[0]] -= 1
        elif name == "li" and stack and stack[-1][0] == "li":
            is_open[stack.pop()[0]] -= 1
        node, boiler, article, link = stack[-1][1:] if stack else outside
        marks = " ".join(x for c in CLASSES.findall(m[3]) for x in c if x) if m[3] else ""
        own = xxh64_intdigest(f"{name}.{marks}" if marks else name, node)
        if name in ("header", "h1") and not (marks and BOILER.search(marks)):
            bad = boiler or name == "header" and not article
        elif name == "article":
            bad = boiler or bool(marks and (OTHER_ARTICLE.search(marks) or article and BOILER.search(marks)))
        else:
            bad = boiler or name in BOILER_TAGS or bool(marks and name not in ("html", "body", *ARTICLE_TAGS) and BOILER.search(marks))
        yield Token(TAG, own, name, bad, article, link, len(stack))
        if name in RAW:
            close = re.compile(rf"</{name}\b[^>]*(?:>|\Z)", re.IGNORECASE).search(text, at)
            at = close.end() if close else size
            continue
        if name in VOID or m[3].endswith("/") and name not in BLOCK:
            continue
        node, boiler, article, link = own, bad, article or name in ARTICLE_TAGS and not bad, link or name == "a"
        stack.append((name, node, boiler, article, link))
        is_open[name] += 1


def number(token: Token) -> int:
    """The token's 64-bit number: tokens of one kind in one path, and of one text, have the same."""
    if token.kind == TAG:
        return token.node - HALF
    return xxh64_intdigest("/" if token.kind == END else f"\n{' '.join(token.value.split())}", token.node) - HALF


def host_of(url):
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1)), F.lit(""))


def summed(held: dict[tuple[str, int], list[int]], names: list[str]) -> pa.RecordBatch:
    hosts, numbers = zip(*held, strict=True)
    columns = zip(*held.values(), strict=True)
    return pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(numbers, pa.int64()), *[pa.array(c, pa.int64()) for c in columns]], names)


def occurrences(pages: DataFrame, most_held: int = 200_000) -> DataFrame:
    """(host, token, s1, s2, pages, total, place) over pages (host, key, html): two 31-bit sums of the occurrence vector's hashes, the pages and times of a token."""
    names = ["host", "token", "s1", "s2", "pages", "total", "place"]

    def run(batches):
        held: dict[tuple[str, int], list[int]] = {}
        for batch in batches:
            for host, key, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                own: dict[int, list[int]] = {}
                for place, token in enumerate(parse(text or "")):
                    if token.kind < TEXT or token.kind == TEXT and not token.value.isspace():
                        own.setdefault(number(token), [0, place])[0] += 1
                hashes: dict[int, int] = {}
                for token, (n, place) in own.items():
                    h = hashes[n] = hashes.get(n) or xxh64_intdigest(f"{key}:{n}")
                    x = held.setdefault((host, token), [0, 0, 0, 0, 0])
                    for k, v in enumerate((h & 0x7FFFFFFF, h >> 33, 1, n, place)):
                        x[k] += v
                if len(held) > most_held:
                    yield summed(held, names)
                    held = {}
        if held:
            yield summed(held, names)

    rows = pages.select("host", "key", "html").mapInArrow(run, "host string, token long, s1 long, s2 long, pages long, total long, place long")
    return rows.groupBy("host", "token").agg(*[F.sum(c).alias(c) for c in names[2:]])


VECTOR = ("host", "s1", "s2", "pages", "total")
#: Stands for all hosts of fewer than three pages; no host has a line end.
POOL = "\n"


def valid_classes(found: DataFrame, hosts: DataFrame, least_size: int = 3, least_share: float = 0.3) -> DataFrame:
    """(host, token) of the valid classes; found: rows of occurrences; hosts: (host, of_host). Hosts of fewer than three pages are host POOL."""
    both = found.join(hosts, "host")
    values = [F.sum(c).alias(c) for c in ("s1", "s2", "pages", "total", "place")]
    pooled = hosts.where("of_host < 3").agg(F.coalesce(F.sum("of_host"), F.lit(0))).first()[0]
    few = both.where("of_host < 3").groupBy(F.lit(POOL).alias("host"), "token").agg(*values).withColumn("of_host", F.lit(pooled))
    many = both.where("of_host >= 3").select(*few.columns)
    tokens = cut(many.union(few).where((F.col("pages") >= 3) & (F.col("pages") >= F.col("of_host") * least_share)))
    of_class = W.partitionBy(*VECTOR)
    mean = F.col("place") / F.col("pages")
    large = tokens.withColumns({"place": mean, "size": F.count("*").over(of_class), "first": F.min(mean).over(of_class), "last": F.max(mean).over(of_class)}).where(F.col("size") >= least_size)
    classes = large.select(*VECTOR, "size", "first", "last").distinct()
    a, b = large.alias("a"), classes.alias("b")
    # a class within [first, last] of a larger one must lie in one of its gaps: no token of the larger one stands between its own
    same = [F.col(f"a.{c}") == F.col(f"b.{c}") for c in VECTOR[1:]]
    other = ~(same[0] & same[1] & same[2] & same[3])
    cut_by = a.join(b, (F.col("a.host") == F.col("b.host")) & other & (F.col("a.size") > F.col("b.size")) & (F.col("a.place") > F.col("b.first")) & (F.col("a.place") < F.col("b.last")) & (F.col("b.total") == F.col("b.pages")), "inner")
    crossed = cut_by.select(*[F.col(f"b.{c}").alias(c) for c in VECTOR]).distinct()
    return large.join(crossed, list(VECTOR), "left_anti").select("host", "token")


def beside(pages: DataFrame, templates: DataFrame, most_bytes: int = 32 << 20) -> DataFrame:
    """pages with the columns of their host's template, null where it has none."""
    lists = [f.name for f in templates.schema if f.name != "host"]
    held = templates.agg(F.count("*").alias("n"), *[F.sum(F.size(c)).alias(c) for c in lists]).first()
    names = templates.select("host", *[F.col(c).alias(f"own_{c}") for c in lists])
    small = sum(held[c] or 0 for c in lists) * 16 + held.n * 64 <= most_bytes
    both = pages.join(F.broadcast(names) if small else names.hint("merge"), "host", "left")
    return both.select(*pages.columns, *[F.col(f"own_{c}").alias(c) for c in lists])


def masses(pages: DataFrame, pool: list[int], most_held: int = 200_000) -> DataFrame:
    """(host, token, pages, mass, whole, depth) over pages (host, html, tokens) of every section of the template; pool: the one of POOL.

    mass: characters of slots within the section that are neither links nor named boilerplate; whole: those of the whole page.
    """
    names = ["host", "token", "pages", "mass", "whole", "depth"]
    shared = frozenset(pool)

    def run(batches):
        held: dict[tuple[str, int], list[int]] = {}
        sets: dict[tuple[int, ...], frozenset[int]] = {}
        for batch in batches:
            for host, text, template in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                known = of_list(template, sets)
                if not known:
                    host, known = POOL, shared
                own: dict[int, list[int]] = {}
                around: list[tuple[int, int]] = []  # sections of the template that are open, with their depths
                whole = 0
                for token in parse(text or ""):
                    while around and around[-1][0] >= token.depth and token.kind != END:
                        around.pop()
                    if token.kind == TAG and token.value in SECTION and not token.boiler and token.node - HALF in known:
                        own.setdefault(token.node, [0, token.depth + 1, 0])[2] += 1
                        around.append((token.depth, token.node))
                    elif token.kind == TEXT and not (token.boiler or token.link or token.value.isspace() or number(token) in known):
                        n = len(token.value)
                        whole += n
                        for node in {x for _, x in around}:
                            own[node][0] += n
                for node, (mass, depth, times) in own.items():
                    if times == 1:  # a section that comes once on the page
                        x = held.setdefault((host, node - HALF), [0, 0, 0, 0])
                        for k, v in enumerate((1, mass, whole, depth)):
                            x[k] += v
                if len(held) > most_held:
                    yield summed(held, names)
                    held = {}
        if held:
            yield summed(held, names)

    rows = pages.select("host", "html", "tokens").mapInArrow(run, ", ".join(f"{c} {'string' if c == 'host' else 'long'}" for c in names))
    return rows.groupBy("host", "token").agg(*[F.sum(c).alias(c) for c in names[2:]])


def of_list(column, sets: dict[tuple[int, ...], frozenset[int]], most: int = 64) -> frozenset[int]:
    """A list as a set; the sets of the last templates are kept."""
    own = tuple(column.as_py() or ())
    if own not in sets:
        if len(sets) >= most:
            sets.clear()
        sets[own] = frozenset(own)
    return sets[own]


def containers(weighed: DataFrame, least_mass: float = 0.5) -> DataFrame:
    """(host, containers): the sections that hold least_mass of the slots' text, innermost first; negative depths are of sections below the body."""
    heavy = weighed.where((F.col("pages") >= 3) & (F.col("mass") >= F.col("whole") * least_mass) & (F.col("mass") > 0))
    depth = F.round(F.col("depth") / F.col("pages")).cast("long")
    return heavy.groupBy("host").agg(F.sort_array(F.collect_list(F.struct((-depth).alias("depth"), "token"))).alias("containers"))


def templates(pages: DataFrame, least_size: int = 3, least_share: float = 0.3, least_mass: float = 0.5) -> DataFrame:
    """(host, tokens, containers) of each host with a template; pages: (host, key, html)."""
    hosts = cut(pages.groupBy("host").agg(F.count("*").alias("of_host")))
    tokens = valid_classes(occurrences(pages), hosts, least_size, least_share)
    found = cut(tokens.groupBy("host").agg(F.sort_array(F.collect_list("token")).alias("tokens")))
    pool = found.where(F.col("host") == POOL).first()  # the tokens of about 1 / least_share pages
    return cut(found.join(containers(masses(beside(pages, found), pool.tokens if pool else []), least_mass), "host", "left"))


def main_text(text: str, known: frozenset[int], order: list[int], inner: frozenset[int]) -> str:
    """The text of the container's slots; order: containers by preference; inner: those below the body. Without one, names alone decide."""
    tokens = list(parse(text))
    there = {x.node - HALF for x in tokens if x.kind == TAG}
    container = next((c for c in order if c in there), None)
    any_article = container is None and any(x.kind == TEXT and x.article and not x.boiler and not x.value.isspace() for x in tokens)
    blocks, block, within = [], [], -1  # within: the depth of the container that is open
    for token in [*tokens, Token(BREAK, 0, "", False, False, False, 0)]:
        if token.kind != END and token.depth <= within:
            within = -1
        if token.kind == TAG and within < 0 and container is not None and token.node - HALF == container:
            within = token.depth
        if token.kind == BREAK:
            if block:
                line = " ".join(entities.unescape("".join(block)).split())
                if line:
                    blocks.append(line)
                block = []
        elif token.kind == TEXT and not token.boiler:
            if container is not None:
                own = within >= 0 and (container in inner or token.value.isspace() or number(token) not in known)
            else:
                own = token.article if any_article else token.value.isspace() or number(token) not in known
            if own:
                block.append(token.value)
    return " ".join(blocks)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least_size: int = 3, least_share: float = 0.3, least_mass: float = 0.5) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    named = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), host_of(F.col(url_col)).alias("host"), F.xxhash64(id_col, url_col, html_col).alias("key"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))
    found = templates(named, least_size, least_share, least_mass)
    order, inner = F.transform("containers", lambda x: x["token"]), F.transform(F.filter("containers", lambda x: x["depth"] < -2), lambda x: x["token"])
    lists = ("tokens", order.alias("order"), inner.alias("inner"))
    pool = found.where(F.col("host") == POOL).select(*lists).first() or ((), (), ())
    shared = frozenset(pool[0]), list(pool[1] or ()), frozenset(pool[2] or ())
    both = beside(named.select("page_id", "url", "host", "html"), found).select("page_id", "url", "html", *lists)
    kind = both.schema["page_id"].dataType.simpleString()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets: dict[tuple[int, ...], frozenset[int]] = {}
        texts = []
        for page, tokens, order, inner in zip(batch.column(2).to_pylist(), *batch.columns[3:6], strict=True):
            known = of_list(tokens, sets)
            texts.append(main_text(page, known, order.as_py() or [], of_list(inner, sets)) if known else main_text(page, *shared))
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return both.mapInArrow(per_batch(kernel), f"page_id {kind}, url string, text string, n_chars long")
