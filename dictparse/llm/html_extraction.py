"""Main text of web pages by templates deduced from equivalence classes.

A page is a sequence of tokens: tags, and the words between them. A token's role is told apart by its path of open elements. Over the
pages of a host, tokens with one and the same occurrence vector (how often each page holds them) form an equivalence class; vectors
are compared by an additive fingerprint, so counting them is an aggregation with partial sums and no host is gathered. Exact copies
of a page are no evidence of a template. A class is valid if nearly all pages of the host hold it and it has more than one token, a tag among them.
The tags of the valid classes are the template's frame. Classes nest by the frame: a word stays in its class only if it lies between
the same two tags of the frame on nearly all pages that hold it, and what lies between template tokens are slots. Words of a valid
class are boilerplate and go with the template. Inside an article or main element a word's role is told apart by its whole block, as
words of prose recur by chance: all words of a block with one and the same text then have one vector, and are counted as one token.
So a block that the host's pages repeat there goes, and words that stand beside a slot's content stay. Slots inside menus, headers, footers, sidebars, notices, adverts, forms,
comments, scripts and styles are dropped too; the text of the remaining slots is the page's main text: that of the article or main
element where a page has one, else that of the whole body. A page of which nothing would
remain keeps its template's words.

Hosts with fewer than MIN_PAGES pages give no template; their slots are judged by their elements alone.

Edge cases: null or empty html gives an empty text; broken markup is read leniently; repeated rows are extracted each; a null url
counts as a host of its own; an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import html as entities
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Callable, Iterator
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import map_batches, read, texts_of, written

#: Pages that a class needs, and the share of the host's pages that must hold a word of boilerplate.
MIN_PAGES, MIN_SHARE = 5, 0.9
#: Hosts with a template, and bytes of all templates, that are sent to the executors; beyond either each page gets its own part by a join.
MAX_SENT, MAX_BYTES = 200_000, 16 << 20
#: Parts into which a token's pages are dealt in that join.
PARTS = 16

#: Elements whose text is never content, elements without end tag, elements that open a block.
_RAW = frozenset("script style noscript template svg math iframe object canvas textarea select option button head title".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_SKIP = frozenset("nav header footer aside form dialog menu".split()) | _RAW
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
#: Words that mark boilerplate as the last part of a class name, id or role, and as its first part.
_MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertisements advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus disclaimer footer header login masthead menu modal nav navbar navigation newsletter notice notices pagination paywall popup promo promos promotion related recommended recommendations reply replies search share sharing sidebar signup social sponsor sponsored subscribe subscription toolbar contentinfo complementary".split()
)
_FIRST = frozenset("ad ads adv advert advertisement cookie cookies comment comments disqus newsletter promo related recommended share social sidebar nav navbar sponsored breadcrumb breadcrumbs".split())
#: What marks an article as none of the page's own.
_OTHER = frozenset("comment comments reply replies related recommended promo ad ads advert sponsored teaser".split())
_PIECE = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|</?[a-zA-Z](?:[^<>\"']|\"[^\"]*(?:\"|$)|'[^']*(?:'|$))*(?:>|(?=<)|$)|[^<]+|<", re.S)
_NAME, _ATTRIBUTE = re.compile(r"</?([a-zA-Z][^\s/>]*)"), re.compile(r"([^\s=/>\"']+)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)")
_HIDDEN = re.compile(r"\shidden(?=[\s=/>])")
#: Elements whose content is no markup.
_OPAQUE = {t: re.compile(f"</{t}", re.I) for t in "script style textarea title noscript iframe template".split()}
_SPLIT = re.compile(r"[^a-z]+")
_SPACE = re.compile(r"\s+")


def _marked(tag: str, name: str, main: bool) -> bool:
    """Whether class, id or role of a start tag name a part that isn't content."""
    for attribute, value in _ATTRIBUTE.findall(tag):
        attribute, value = attribute.lower(), value.strip("\"'").lower()
        if attribute in ("class", "id", "role"):
            for own in value.split():
                parts = [x for x in _SPLIT.split(own) if x]
                if not parts:
                    continue
                if name in ("article", "main", "body", "html"):
                    if name == "article" and (parts[-1] in _OTHER or parts[0] in _OTHER):
                        return True
                elif parts[0] not in ("has", "with", "no", "is") and (parts[0] in _FIRST or parts[-1] in _MARKS and not (main and parts[-1] == "header")):
                    return True
        if attribute == "aria-hidden" and value == "true":
            return True
    return " hidden" in tag and _HIDDEN.search(tag) is not None


class Page:
    """The tokens of a page with their path, and its text in blocks.

    Each run of text knows its block, its path, and whether it stands in an element that is never content.
    """

    def __init__(self, source: str):
        self.runs: list[tuple[int, str, str, bool, bool, int]] = []  # block, path, text, skipped, inside the article, tags before it
        self.tags: list[str] = []
        self.has_main = False
        stack: list[tuple[str, bool, bool]] = []  # name, skipped, main
        block, at = 0, 0
        while m := _PIECE.match(source, at):
            piece, at = m[0], m.end()
            if not piece:
                break
            if piece[0] != "<" or len(piece) < 2 or not (piece[1].isalpha() or piece[1] == "/"):
                if piece[:2] in ("<!", "<?"):
                    continue
                if stack:
                    top = stack[-1]
                    self.runs.append((block, "/".join(x[0] for x in stack[-4:]), piece, top[1], top[2], len(self.tags)))
                else:
                    self.runs.append((block, "", piece, False, False, len(self.tags)))
                continue
            name = _NAME.match(piece)
            if not name:
                continue
            tag = name[1].lower()
            if tag in _BLOCK:
                block += 1
            elif tag == "br" and stack:
                self.runs.append((block, "", " ", stack[-1][1], stack[-1][2], len(self.tags)))
            if piece[1] == "/":
                self.tags.append(f"</{tag}>")
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == tag:
                        del stack[k:]
                        break
                continue
            skipped, main = (stack[-1][1], stack[-1][2]) if stack else (False, False)
            if tag in ("article", "main"):
                main = True
            # an article's own heading group belongs to it
            skipped = skipped or (tag in _SKIP and not (tag == "header" and main)) or _marked(piece, tag, main)
            self.has_main |= main and not skipped
            self.tags.append(f"{'/'.join(x[0] for x in stack[-3:])}<{tag}>")
            if tag in _OPAQUE:
                end = _OPAQUE[tag].search(source, at)
                at = end.start() if end else len(source)
            if tag not in _VOID and not piece.endswith("/>"):
                if tag == "p" and stack and stack[-1][0] == "p":
                    stack.pop()
                stack.append((tag, skipped, main))

    def roles(self) -> Iterator[tuple[int, str, int]]:
        """(block, token, tags before it) of text that could be boilerplate: words of the body, or of an article its blocks as one."""
        if not self.has_main:
            for block, path, text, skipped, _, before in self.runs:
                if not skipped:
                    for w in text.split():
                        yield block, f"{path} {w}", before
            return
        import xxhash

        inside = ((run[0], run[1], w, run[5]) for run in self.runs if run[4] and not run[3] for w in run[2].split())
        for block, own in groupby(inside, lambda x: x[0]):
            _, path, word, before = next(own)
            hashed = xxhash.xxh3_128(f"{path} {word}".encode())
            for _, p, w, _ in own:
                hashed.update(f"\n{p} {w}".encode())
            yield block, f"{path} {hashed.hexdigest()}", before

    def tokens(self) -> Counter[str]:
        """How often the page holds each of its tokens."""
        return Counter([*self.tags, *(token for _, token, _ in self.roles())])

    def places(self, template: frozenset[str]) -> dict[str, set[tuple[str, str]]]:
        """For each word of the template the pairs of its tags that the word lies between."""
        frame = [k for k, t in enumerate(self.tags) if t in template]
        out: dict[str, set[tuple[str, str]]] = {}
        for _, token, before in self.roles():
            if token in template:
                k = bisect_left(frame, before)
                out.setdefault(token, set()).add((self.tags[frame[k - 1]] if k else "", self.tags[frame[k]] if k < len(frame) else ""))
        return out

    def text(self, template: frozenset[str] = frozenset()) -> str:
        """Text of the slots that remain, block by block; runs (inside an article, blocks) all of whose words belong to the template are no slots."""
        out: list[str] = []
        at, parts = -1, []

        def close() -> None:
            t = _SPACE.sub(" ", entities.unescape("".join(parts))).strip()
            if t:
                out.append(t)

        gone = {block for block, token, _ in self.roles() if token in template} if template and self.has_main else ()
        for block, path, run, skipped, main, _ in self.runs:
            if skipped or (self.has_main and not main) or block in gone:
                continue
            if template and not main and all(f"{path} {w}" in template for w in run.split()):
                run = " "
            if block != at:
                close()
                at, parts = block, []
            parts.append(run)
        close()
        return "\n".join(out) if out or not template else self.text()


def host_of(url: str | None) -> str:
    m = re.match(r"[a-zA-Z][\w+.-]*://(?:[^/@]*@)?([^/:?#]*)", url or "")
    return m[1].lower() if m else url or ""


def classes(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(host, token, vector, pages): tokens that at least MIN_PAGES different pages of the host hold, and their vectors' fingerprints."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        held: dict[tuple[str, str], list] = {}

        def out() -> pa.RecordBatch:
            columns = [[k[0] for k in held], [k[1] for k in held], *([v[n] for v in held.values()] for n in range(3))]
            kinds = (pa.string(), pa.string(), pa.int64(), pa.int64(), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["host", "token", "vector", "pages", "some"])

        for b in batches:
            for u, t in zip(b.column("url").to_pylist(), texts_of(b, "html"), strict=True):
                p, host, page = Page(t.decode()), host_of(u), xxhash.xxh3_64_intdigest(t) >> 1
                for token, n in p.tokens().items():
                    v = held.get((host, token))
                    if v is None:
                        v = held[host, token] = [0, 0, []]
                    v[0] = (v[0] + (page ^ n * 0x9E3779B97F4A7C15) * 0xC2B2AE3D27D4EB4F) & (1 << 62) - 1
                    v[1] += 1
                    if len(v[2]) < MIN_PAGES and page not in v[2]:
                        v[2].append(page)
                if len(held) > 300_000:
                    yield out()
                    held = {}
        yield out()

    narrow = pages.select(F.col(url).alias("url"), F.col(html).alias("html"))
    counted = map_batches(narrow, run, "host string, token string, vector long, pages long, some array<long>")
    vector = F.pmod(F.sum(F.col("vector").cast("decimal(38,0)")), F.lit(1 << 62).cast("decimal(38,0)")).cast("long")
    # at most MIN_PAGES page numbers from each task
    different = F.size(F.array_distinct(F.flatten(F.collect_list("some"))))
    return counted.groupBy("host", "token").agg(vector.alias("vector"), F.sum("pages").alias("pages"), different.alias("different")).where(F.col("different") >= MIN_PAGES).drop("different")


def templates(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(host, token) of every token of a host's template: classes that most of the host's pages hold.

    A class of one tag or word alone says nothing; words need a class that holds a tag of the page's frame too, so that they lie
    between the same template tokens on each page.
    """
    tokens = written(classes(pages, url, html), "classes")
    whole = tokens.groupBy("host").agg(F.max("pages").alias("all"))
    framed = tokens.groupBy("host", "vector").agg(F.max(F.when(F.col("token").contains("<"), 1).otherwise(0)).alias("framed"), F.count("*").alias("size"))
    return tokens.join(framed, ["host", "vector"]).join(whole, "host").where((F.col("framed") == 1) & (F.col("size") > 1) & (F.col("pages") >= MIN_SHARE * F.col("all"))).select("host", "token")


def nested(pages: DataFrame, tokens: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(host, token) of the template's words that lie between the same tags of the template on nearly all pages that hold them."""
    source, template = with_template(pages.select(F.col(url).alias("url"), F.col(html).alias("html")), tokens)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        held: Counter[tuple[str, str, int]] = Counter()

        def out() -> pa.RecordBatch:
            columns = [pa.array([k[n] for k in held], t) for n, t in enumerate((pa.string(), pa.string(), pa.int64()))]
            return pa.RecordBatch.from_arrays([*columns, pa.array([*held.values()], pa.int64())], names=["host", "token", "place", "n"])

        for b in batches:
            for u, words, t in zip(b.column("url").to_pylist(), b.column("words").to_pylist(), texts_of(b, "html"), strict=True):
                host = host_of(u)
                for token, places in Page(t.decode()).places(template(u, words)).items():
                    held[host, token, xxhash.xxh3_64_intdigest(repr(sorted(places)).encode()) >> 1] += 1
                if len(held) > 300_000:
                    yield out()
                    held.clear()
        yield out()

    counted = map_batches(source, run, "host string, token string, place long, n long").groupBy("host", "token", "place").agg(F.sum("n").alias("n"))
    return counted.groupBy("host", "token").agg(F.max("n").alias("most"), F.sum("n").alias("all")).where(F.col("most") >= MIN_SHARE * F.col("all")).select("host", "token")


def with_template(narrow: DataFrame, frame: DataFrame) -> tuple[DataFrame, Callable[[str | None, list[str] | None], frozenset[str]]]:
    """(url, html, further columns) with `words`, and the function of url and `words` that gives the tokens of the host's template.

    All templates are sent where hosts and bytes are few. Else `words` holds those of the template's tokens that the page has: its
    tokens are joined with the templates' on host and token, so no template is ever in one row, however large it is.
    """
    none: frozenset[str] = frozenset()
    whole = frame.agg(F.countDistinct("host").alias("hosts"), F.coalesce(F.sum(F.octet_length("token")), F.lit(0)).alias("bytes")).first()
    if whole["hosts"] <= MAX_SENT and whole["bytes"] <= MAX_BYTES:
        rows = frame.groupBy("host").agg(F.collect_list("token").alias("words")).collect()
        sent = narrow.sparkSession.sparkContext.broadcast({r.host: frozenset(r.words) for r in rows})
        return narrow.withColumn("words", F.lit(None).cast("array<string>")), lambda url, _: sent.value.get(host_of(url), none)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row, u, t in zip(b.column("row").to_pylist(), b.column("url").to_pylist(), texts_of(b, "html"), strict=True):
                own = [*Page(t.decode()).tokens()]
                columns = [pa.array([row] * len(own), pa.int64()), pa.array([host_of(u)] * len(own), pa.string()), pa.array(own, pa.string())]
                yield pa.RecordBatch.from_arrays(columns, names=["row", "host", "token"])

    numbered = written(narrow.withColumn("row", F.monotonically_increasing_id()), "numbered-pages")
    parts = frame.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1))))
    tokens = map_batches(numbered.select("row", "url", "html"), run, "row long, host string, token string")
    tokens = tokens.withColumn("part", F.pmod(F.xxhash64("row"), F.lit(PARTS)).cast("int"))
    found = tokens.join(parts, ["host", "token", "part"]).groupBy("row").agg(F.collect_list("token").alias("words"))
    return numbered.join(found, "row", "left").drop("row"), lambda _, words: frozenset(words or ())


def extract(pages: DataFrame, page: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """page, url, text and n_chars of every row."""
    frame = written(nested(pages, written(templates(pages, url, html), "templates"), url, html), "nested")
    narrow = pages.select(F.col(page).alias("page"), F.col(url).alias("url"), F.col(html).alias("html"))
    kind = pages.schema[page].dataType.simpleString()
    source, template = with_template(narrow, frame)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            urls, joined = b.column("url").to_pylist(), b.column("words").to_pylist()
            found = [Page(t.decode()).text(template(u, words)) for u, words, t in zip(urls, joined, texts_of(b, "html"), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("page"), b.column("url"), pa.array(found, pa.string()), pa.array([len(x) for x in found], pa.int64())], names=["page", "url", "text", "n_chars"])

    return map_batches(source, run, f"page {kind}, url string, text string, n_chars long").withColumnRenamed("page", page)


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(read(spark, sf_dir, "pages"))


QUERIES = {"op1_html_extraction": op1_html_extraction}
SQL: dict[str, str] = {}
