"""Main text of web pages, with site templates removed.

Every page is parsed into elements, and the subtree of every block is hashed twice:
over its tag, class, text and children, and as a frame: the way to it and its tags
and classes alone. Spark counts for each host on how many different pages each
occurs, and what recurs on many pages of its host is deleted: blocks that say the
same, and frames that are thin wherever they occur, as menus, notices, adverts and
footers are whose words differ from page to page. A frame is thin when half of its
words or more are in links, or when it has up to ``THIN_WORDS`` words and is outside
``article`` and ``main``; headings, paragraphs and what holds them are no frames. A
page that frames would leave without a word keeps them.

Names come second, for hosts with too few pages to count: what calls itself furniture
(menus, headers, footers, sidebars, notices, adverts, forms, comments) goes on any
page, and scripts and styles always.

A page counts once for each different content of its main part, so copies of an
article do not make its parts a template. How many pages make a template grows with
the root of the host's pages, so a block of one section or language is found on
large hosts too; headings and paragraphs of an ``article`` or ``main`` are prose and
need ``PROSE_TIMES`` as many.

The recurring subtrees are broadcast while their number is below a checked
bound; beyond it, each page gets its own by a join.

Defined results: null html gives the empty string; broken markup is read as browsers do
where that is simple (open paragraphs end at the next block, stray ends are
ignored); a page without article or main is read from its body; repeated rows are
repeated; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import html
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from subgraph_engine.storage import only_result, text_batches, written_table

#: A subtree is a template when it is on at least so many different pages of its host and
#: on at least the square root of their number: a quarter of 16 pages, a tenth of 100.
LEAST_PAGES = 4
#: Prose of the main part needs so many times the pages.
PROSE_TIMES = 4
#: Words of a frame that is thin without links, and the share of its pages on which it has to be.
THIN_WORDS = 40
THIN_SHARE = 0.9
#: Template subtrees that are broadcast, 8 bytes each, at most.
BROADCAST_TEMPLATES = 1_000_000

# Element names by their role in HTML, and words that name furniture.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary"
    " table tbody td tfoot th thead title tr ul".split()
)
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre".split())
DROPPED = frozenset(
    "head nav footer aside form script style noscript template iframe object svg math canvas audio video button select option"
    " textarea input label fieldset menu dialog search".split()
)
RAW = frozenset("script style textarea title iframe noscript xmp noembed noframes".split())
FURNITURE = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adbox adslot banner sponsor sponsored promo promotion promoted"
    " cookie cookies consent gdpr notice notices notification alert alerts popup modal overlay newsletter subscribe subscription"
    " signup sidebar menu menus nav navbar navigation topnav subnav breadcrumb breadcrumbs footer comment comments commentlist"
    " reply replies respond disqus discussion share sharing social related recommended recommendations widget widgets pagination"
    " pager login toolbar masthead skip copyright paywall outbrain taboola".split()
)
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar toolbar".split())
#: An end of a paragraph may be left out before these; the others end what is of their own kind.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
SCOPES = frozenset("ul ol dl table".split())

_TAG = re.compile(
    r"<!--.*?(?:--!?>|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S
)
_NAMES = re.compile(r"""\b(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
_WORDS = re.compile(r"[a-z]+", re.I)
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_RAW_END = {t: re.compile(rf"</{t}(?=[\s/>])", re.I) for t in RAW}


class Page:
    """The elements of a page in document order, and its runs of text."""

    def __init__(self, markup: str):
        self.tag, self.parent, self.named, self.digest = ["#"], [-1], [""], [0]
        #: the way to an element, its shape without words, whether it holds prose, and its words, all and in links
        self.way, self.shape, self.has_prose, self.words, self.linked = [0], [0], [False], [0], [0]
        self.furniture = [False]
        self.pieces: list[tuple[int, str | None]] = []  # (element, text), text None: a block begins or ends
        self._parts: list[list[str]] = [[]]
        self._open = [0]
        self._read(markup)
        while self._open:
            self._close()

    def _read(self, markup: str) -> None:
        at, end = 0, len(markup)
        while at < end:
            m = _TAG.search(markup, at)
            self._text(markup[at : m.start() if m else end])
            if not m:
                return
            at = m.end()
            if not m[2]:
                continue
            tag = m[2].lower()
            if m[1]:
                self._end(tag)
                continue
            self._start(tag, m[3])
            if tag in RAW:
                stop = _RAW_END[tag].search(markup, at)
                self._text(markup[at : stop.start() if stop else end])
                at = stop.start() if stop else end

    def _text(self, text: str) -> None:
        if text:
            text = html.unescape(text) if "&" in text else text
            self.pieces.append((self._open[-1], text))
            if word := text.strip():
                self._parts[self._open[-1]].append(word)
                self.words[self._open[-1]] += len(word.split())

    def _start(self, tag: str, attributes: str) -> None:
        if tag in BLOCK:
            self._pop_through({"p"}, SCOPES if tag != "p" else SCOPES)
        if tag in ENDS:
            self._pop_through(ENDS[tag], SCOPES)
        if tag == "br":
            self.pieces.append((self._open[-1], " "))
        if tag in VOID and tag != "hr":
            return
        names, furniture = self._named(tag, attributes) if attributes else ("", False)
        i = len(self.tag)
        self.tag.append(tag)
        self.parent.append(self._open[-1])
        self.named.append(names)
        self.digest.append(0)
        own = f"{tag}\x1f{names}"
        self.way.append(_hashed(f"{self.way[self._open[-1]]:x}\x1f{own}"))
        self.shape.append(_hashed(own))
        self.has_prose.append(tag in PROSE)
        self.words.append(0)
        self.linked.append(0)
        self._parts.append([])
        self.furniture.append(furniture or tag in DROPPED)
        self._open.append(i)
        if tag in BLOCK:
            self.pieces.append((i, None))
        if tag in VOID or attributes.endswith("/") and tag in ("svg", "path"):
            self._close()

    def _named(self, tag: str, attributes: str) -> tuple[str, bool]:
        names, words = [], set()
        hidden = False
        for m in _NAMES.finditer(attributes):
            kind, value = m[1].lower(), m[2] or m[3] or m[4] or ""
            if kind == "hidden" or kind == "aria-hidden" and value.lower() == "true" and tag not in ("i", "span", "a"):
                hidden = True
            elif kind == "role":
                hidden |= value.lower() in ROLES
            elif kind in ("class", "id"):
                names.append(value)
                for name in value.split():
                    parts = [w.lower() for w in _WORDS.findall(_CAMEL.sub(" ", name))]
                    words.update(parts)
        if tag in ("html", "body", "main", "h1"):
            return " ".join(names), False
        if tag == "article":
            words &= {"comment", "comments", "reply", "ad", "advert", "sponsored", "promo", "related"}
        return " ".join(names), hidden or bool(words & FURNITURE)

    def _pop_through(self, tags: set[str], scope: frozenset[str]) -> None:
        for k in range(len(self._open) - 1, 0, -1):
            tag = self.tag[self._open[k]]
            if tag in tags:
                while len(self._open) > k:
                    self._close()
                return
            if tag in scope or tag in BLOCK and tag not in tags and tag not in ("p",) and "p" in tags:
                return

    def _end(self, tag: str) -> None:
        inline = tag not in BLOCK
        for k in range(len(self._open) - 1, 0, -1):
            own = self.tag[self._open[k]]
            if own == tag:
                while len(self._open) > k:
                    self._close()
                return
            if inline and own in BLOCK:
                return

    def _close(self) -> None:
        i = self._open.pop()
        parts = self._parts[i]
        if self.tag[i] == "a":
            self.linked[i] = self.words[i]
        if self._open:
            up = self._open[-1]
            self.words[up] += self.words[i]
            self.linked[up] += self.linked[i]
            self.has_prose[up] |= self.has_prose[i] and self.words[i] > 0
            self.shape[up] = _hashed(f"{self.shape[up]:x}\x1f{self.shape[i]:x}")
        if parts:
            said = "\x1f".join([self.tag[i], self.named[i], *parts])
            self.digest[i] = int.from_bytes(hashlib.blake2b(said.encode("utf-8", "replace"), digest_size=8).digest(), "little", signed=True)
            if self._open:
                self._parts[self._open[-1]].append(f"{self.digest[i]:x}")
        self._parts[i] = []
        if self.tag[i] in BLOCK:
            self.pieces.append((i, None))

    def scope(self) -> list[bool]:
        """Which elements belong to the main part, furniture left out of account."""
        gone = self.dropped(frozenset(), "")
        for kind in ("article", "main", "body", "#"):
            roots = {i for i, t in enumerate(self.tag) if t == kind and not gone[i]}
            if kind == "main" and not roots:
                roots = {i for i, n in enumerate(self.named) if not gone[i] and self.tag[i] in ("div", "section") and n in ("content", "main", "main-content")}
            if roots:
                break
        inside = [False] * len(self.tag)
        for i in range(len(self.tag)):
            inside[i] = i in roots or i > 0 and inside[self.parent[i]]
        self.in_article = [x and kind in ("article", "main") for x in inside]
        return inside

    def dropped(self, templates, host: str, frames: bool = True) -> list[bool]:
        """Furniture and templates, with all that is below them."""
        gone = [False] * len(self.tag)
        for i in range(1, len(self.tag)):
            gone[i] = gone[self.parent[i]] or self.furniture[i] or self.tag[i] == "header" and not self._within_article(i)
            if templates and not gone[i] and self.candidate(i):
                gone[i] = template_key(host, self.digest[i], SAYING + self.prose(i)) in templates
                if frames and not gone[i] and self.frame(i):
                    gone[i] = template_key(host, self.frame_digest(i), FRAME) in templates
        return gone

    def frame(self, i: int) -> bool:
        """Whether a candidate may recur as a frame."""
        return not self.has_prose[i] and not self._under_prose(i, anywhere=True)

    def frame_digest(self, i: int) -> int:
        return _hashed(f"{self.way[i]:x}\x1f{self.shape[i]:x}")

    def thin(self, i: int) -> bool:
        """Mostly links, or few words outside the main part."""
        return 2 * self.linked[i] >= self.words[i] or self.words[i] <= THIN_WORDS and not self.in_article[i]

    def _within_article(self, i: int) -> bool:
        while i > 0:
            i = self.parent[i]
            if self.tag[i] in ("article", "main"):
                return True
        return False

    def candidate(self, i: int) -> bool:
        """Whether a subtree may be a template: a block with text."""
        tag = self.tag[i]
        return bool(self.digest[i]) and tag in BLOCK and tag not in ("html", "body", "head", "title", "article", "main")

    def prose(self, i: int) -> bool:
        """Whether an element is prose of the main part."""
        return self.in_article[i] and (self.tag[i] in PROSE or self._under_prose(i))

    def _under_prose(self, i: int, anywhere: bool = False) -> bool:
        while self.parent[i] > 0 and (anywhere or self.in_article[i]):
            i = self.parent[i]
            if self.tag[i] in PROSE:
                return True
        return False

    def subtrees(self) -> tuple[int, dict[tuple[int, int], bool]]:
        """A digest of the page's main part; and (digest, kind) of its candidate subtrees, with whether they are thin throughout."""
        inside = self.scope()
        main = hashlib.blake2b(digest_size=8)
        for i, text in self.pieces:
            if text and inside[i]:
                main.update(text.strip().encode("utf-8", "replace"))
        found: dict[tuple[int, int], bool] = {}
        for i in range(1, len(self.tag)):
            if self.candidate(i):
                found[self.digest[i], SAYING + self.prose(i)] = True
                if self.frame(i):
                    key = (self.frame_digest(i), FRAME)
                    found[key] = found.get(key, True) and self.thin(i)
        return int.from_bytes(main.digest(), "little", signed=True), found

    def main_text(self, templates, host: str) -> str:
        return self._text_left(templates, host, True) or self._text_left(templates, host, False)

    def _text_left(self, templates, host: str, frames: bool) -> str:
        inside = self.scope()
        gone = self.dropped(templates, host, frames)
        blocks, now = [], []
        for i, text in self.pieces:
            if text is None:
                if now:
                    blocks.append(" ".join("".join(now).split()))
                    now = []
            elif inside[i] and not gone[i]:
                now.append(text)
        blocks.append(" ".join("".join(now).split()))
        return " ".join(b for b in blocks if b)


#: Kinds of subtrees: by what they say, the same for prose of the main part, and frames.
SAYING, SAYING_PROSE, FRAME = 0, 1, 2


def _hashed(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "replace"))


def template_key(host: str, digest: int, kind: int = SAYING) -> int:
    mixed = hashlib.blake2b(f"{host}\x1f{digest}\x1f{kind}".encode("utf-8", "replace"), digest_size=8).digest()
    return int.from_bytes(mixed, "little", signed=True)


def host_of(url: str | None) -> str:
    rest = (url or "").partition("://")[2] or (url or "")
    return re.split(r"[/?#]", rest, maxsplit=1)[0].rpartition("@")[2].lower()


def subtree_rows(pages: DataFrame) -> DataFrame:
    """host, main (digest of the main part), key (of host and subtree), kind, thin; distinct within a page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, mains, keys, kinds, thin = [], [], [], [], []
            for url, markup in zip(batch.column("url").to_pylist(), batch.column("html").to_pylist()):
                host = host_of(url)
                main, found = Page(markup or "").subtrees()
                hosts += [host] * (len(found) + 1)
                mains += [main] * (len(found) + 1)
                keys += [None, *(template_key(host, *f) for f in found)]
                kinds += [SAYING, *(f[1] for f in found)]
                thin += [True, *found.values()]
            columns = [pa.array(hosts, pa.string()), pa.array(mains, pa.int64()), pa.array(keys, pa.int64()), pa.array(kinds, pa.int32()), pa.array(thin, pa.bool_())]
            yield pa.RecordBatch.from_arrays(columns, ["host", "main", "key", "kind", "thin"])

    return pages.select("url", "html").mapInArrow(run, "host string, main long, key long, kind int, thin boolean")


def find_templates(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """key of every subtree that recurs on many different pages of its host."""
    return only_result(spark, "html-templates", lambda: _templates(spark, pages))


def _templates(spark: SparkSession, pages: DataFrame) -> DataFrame:
    once = subtree_rows(pages).groupBy("host", "key", "kind", "main").agg(F.bool_and("thin").alias("thin"))
    counts = once.groupBy("host", "key", "kind").agg(F.count(F.lit(1)).alias("pages"), F.count_if("thin").alias("thin"))
    counts = written_table(spark, counts, "html-subtrees")
    sites = counts.filter("key is null").select("host", F.col("pages").alias("all_pages"))
    often = counts.filter(f"key is not null and pages >= {LEAST_PAGES} and thin >= {THIN_SHARE} * pages").join(sites, "host")
    least = F.greatest(F.lit(float(LEAST_PAGES)), F.sqrt("all_pages")) * F.when(F.col("kind") == SAYING_PROSE, PROSE_TIMES).otherwise(1)
    return often.filter(F.col("pages") >= least).select("key").distinct()


RESULT = T.StructType(
    [
        T.StructField("page_id", T.LongType()),
        T.StructField("url", T.StringType()),
        T.StructField("text", T.StringType()),
        T.StructField("n_chars", T.LongType()),
    ]
)


def extract(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: the main text of every page."""
    text_batches(spark)
    rows = pages.select(F.col("page_id").cast("long"), "url", "html")
    templates = find_templates(spark, rows)
    if templates.count() <= BROADCAST_TEMPLATES:
        keys = spark.sparkContext.broadcast(frozenset(templates.toArrow().column(0).to_pylist()))
        return rows.mapInArrow(lambda batches: _texts(batches, lambda: keys.value), RESULT)
    return _extract_joined(rows, templates)


def _extract_joined(rows: DataFrame, templates: DataFrame) -> DataFrame:
    """The same with each page's templates found by a join."""
    name = F.xxhash64("page_id", "url", "html")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, keys = [], []
            for own, url, markup in zip(*(batch.column(c).to_pylist() for c in ("name", "url", "html"))):
                host = host_of(url)
                found = Page(markup or "").subtrees()[1]
                names += [own] * len(found)
                keys += [template_key(host, *f) for f in found]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(keys, pa.int64())], ["name", "key"])

    has = rows.select(name.alias("name"), "url", "html").mapInArrow(run, "name long, key long")
    # a page's list is as long as its own elements
    own = has.join(templates, "key", "left_semi").groupBy("name").agg(F.collect_set("key").alias("templates"))
    joined = rows.withColumn("name", name).join(own, "name", "left").select("page_id", "url", "html", "templates")
    return joined.mapInArrow(lambda batches: _texts(batches, None), RESULT)


def _texts(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    templates = shared() if shared else None
    for batch in batches:
        texts = []
        own = batch.column("templates").to_pylist() if shared is None else [templates] * batch.num_rows
        for url, markup, keys in zip(batch.column("url").to_pylist(), batch.column("html").to_pylist(), own):
            texts.append(Page(markup or "").main_text(frozenset(keys or ()), host_of(url)))
        columns = [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())]
        yield pa.RecordBatch.from_arrays(columns, ["page_id", "url", "text", "n_chars"])


def texts_of_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(spark, spark.read.parquet(f"{sf_dir}/pages.parquet"))
