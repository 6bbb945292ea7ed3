"""Main text of web pages by host-wide consensus on container paths (operator 10)."""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.llm.shared import read_table, written
from objann.llm.url_filter import host_of

MAX_BROADCAST_HOSTS = 200_000

RAW = "script|style|noscript|template|textarea|title|iframe|svg|select|button"
_token = re.compile(
    rf"<!--.*?(?:-->|\Z)|<({RAW})\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-z][a-z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)>|<(/?)([a-z][a-z0-9:-]*)([^>]*)(?:>|\Z)|<[!?][^>]*(?:>|\Z)",
    re.S | re.I,
)
_attribute = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_digits = re.compile(r"\d+")
_words = re.compile(r"[a-z]+")

CONTAINERS = frozenset("html body article main section div td center table tbody tr ul ol dl li blockquote figure details".split())
BLOCKS = CONTAINERS | frozenset("p h1 h2 h3 h4 h5 h6 pre dt dd th figcaption hr address summary caption thead tfoot header footer nav aside form fieldset head menu dialog".split())
VOID = frozenset("hr br img input meta link area base col embed source track wbr".split())
DROPPED = frozenset("nav footer aside form head menu dialog fieldset".split())
PARAGRAPHS = frozenset("p pre blockquote li dd td h1 h2 h3 h4 h5 h6".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
HEADER_NAMES = frozenset("header masthead".split())
ARTICLE_NAMES = frozenset("article post entry story hentry".split())
BAD_NAMES = frozenset(
    "nav navbar navigation menu footer sidebar breadcrumb breadcrumbs cookie cookies consent notice notices banner ad ads advert adverts advertisement "
    "promo sponsor sponsored comment comments respond share sharing social related newsletter popup modal login signup subscribe toolbar pagination pager widget copyright disclaimer".split()
)


def path_name(parent: int, label: str) -> int:
    """64 bits that name a container path: its parent's name and its own tag and classes."""
    return xxhash.xxh3_64_intdigest(label.encode("utf-8", "surrogatepass"), seed=parent & (1 << 64) - 1) - (1 << 63)


class Page:
    """Blocks of text in page order, each with the containers around it, in one pass over the tags.

    A block is (text, link characters, is paragraph, container, dropped).  Scripts, styles and
    comments are no text; menus, footers, sidebars, forms and elements whose class, id or role
    names such a thing are dropped with all they hold.  A header, by tag or name, is dropped outside
    of an article; inside, its headings stay.  An article is an article element or one with a class, id or role
    that says so.  A path is kept as its depth and a 64-bit name, so that deep nesting costs no more than its tags.
    """

    def __init__(self, html: str):
        self.paths: list[int] = []
        self.depths: list[int] = []
        self.parents: list[int] = []
        self.in_article: list[bool] = []
        self.blocks: list[tuple[str, int, bool, int, bool]] = []
        self._text: list[str] = []
        self._links = 0
        stack: list[tuple[str, int, bool, bool, bool]] = []  # tag; container, dropped, article's header, article around it
        opened: dict[str, int] = {}
        container, dropped, paragraph, link, in_header, article = self._open("root", -1, False), False, False, 0, False, False
        heading = 0
        at = 0
        for m in _token.finditer(html):
            if m.start() > at:
                self._add(html[at : m.start()], link)
            at = m.end()
            raw, end, tag, rest = m.group(1), m.group(2), m.group(3), m.group(4)
            if tag is None:
                end, tag, rest = m.group(5), m.group(6), m.group(7)
            if raw or tag is None:
                continue
            tag = tag.lower()
            if tag == "a":
                link = 0 if end else 1
                continue
            if tag not in BLOCKS:
                if tag == "br":
                    self._text.append(" ")
                continue
            self._close(container, paragraph, dropped or (in_header and not heading))
            paragraph, link = False, 0
            if tag in VOID:
                continue
            if end:
                heading = 0 if tag in HEADINGS else heading
                if opened.get(tag):
                    while stack:
                        name, container, dropped, in_header, article = stack.pop()
                        opened[name] -= 1
                        if name == tag:
                            break
                continue
            if tag in ("p", *HEADINGS) or tag in ("pre", "dt"):
                paragraph, heading = True, int(tag in HEADINGS)
                continue
            if tag == "li" and stack and stack[-1][0] == "li":
                _, container, dropped, in_header, article = stack.pop()
                opened["li"] -= 1
            names = self._names(rest) if rest and "=" in rest else ()
            words = {n for name in names for n in _words.findall(name)} if names else ()
            stack.append((tag, container, dropped, in_header, article))
            opened[tag] = opened.get(tag, 0) + 1
            heading = 0
            top = tag in ("html", "body", "article", "main")
            if tag == "header" or (not top and not HEADER_NAMES.isdisjoint(words)):
                in_header = in_header or article
                dropped = dropped or not article
            elif tag in DROPPED or (not top and not BAD_NAMES.isdisjoint(words)):
                dropped = True
            article = article or tag == "article" or (not dropped and not ARTICLE_NAMES.isdisjoint(names))
            paragraph = tag in PARAGRAPHS
            if tag in CONTAINERS and tag not in ("html", "tbody", "tr"):
                label = ".".join([tag, *sorted({_digits.sub("#", n) for n in names})])
                container = self._open(label, container, article or tag == "main")
        if at < len(html):
            self._add(html[at:], link)
        self._close(container, paragraph, dropped or (in_header and not heading))

    @staticmethod
    def _names(attributes: str) -> list[str]:
        return [n for m in _attribute.finditer(attributes) for n in (m.group(2) or m.group(3) or m.group(4) or "").lower().split()]

    def _open(self, label: str, parent: int, article: bool) -> int:
        self.paths.append(path_name(self.paths[parent] if parent >= 0 else 0, label))
        self.depths.append(self.depths[parent] + 1 if parent >= 0 else 0)
        self.parents.append(parent)
        self.in_article.append(article)
        return len(self.paths) - 1

    def _add(self, text: str, link: int) -> None:
        self._text.append(text)
        if link:
            self._links += len(text)

    def _close(self, container: int, paragraph: bool, dropped: bool) -> None:
        if self._text:
            text = " ".join(html_lib.unescape("".join(self._text)).split())
            if text:
                self.blocks.append((text, min(self._links, len(text)), paragraph, container, dropped))
            self._text = []
        self._links = 0

    def scores(self, links_count: bool = False) -> dict[int, float]:
        """Score by path: all kept text below a container that is no link, less the links and the dropped text below it.

        A container that holds the whole article so beats each of its sections, lists and tables,
        and one that holds the page's menus and footers too falls behind.  With ``links_count`` links
        are text like other text, and only containers of an article or main part count.
        """
        below = [0.0] * len(self.paths)
        for text, links, paragraph, container, dropped in self.blocks:
            below[container] += -len(text) if dropped else (len(text) - (0 if links_count else 2 * links)) * (1.0 if paragraph else 0.4)
        for k in range(len(below) - 1, 0, -1):
            below[self.parents[k]] += below[k]
        found: dict[int, float] = {}
        for path, score, article in zip(self.paths, below, self.in_article):
            if article or not links_count:
                found[path] = found.get(path, 0.0) + score
        return found

    def text_in(self, path: int) -> str:
        """Kept blocks in containers of this path, joined by empty lines."""
        inside = [p == path for p in self.paths]
        for k, parent in enumerate(self.parents):
            inside[k] = inside[k] or (parent >= 0 and inside[parent])
        return "\n\n".join(b[0] for b in self.blocks if inside[b[3]] and not b[4])

    def best(self) -> list[tuple[int, int, float]]:
        """(path, depth, score) of all paths of positive score, best first, ties to the deeper.

        Where every container has more links than text, as in an article that is all links, links count as text.
        """
        depth = dict(zip(self.paths, self.depths))
        for links_count in (False, True):
            if good := [(p, depth[p], s) for p, s in self.scores(links_count).items() if s > 0]:
                return sorted(good, key=lambda x: (-x[2], -x[1], x[0]))
        return []

    def _within(self, path: int, outer: int) -> bool:
        """Whether containers of ``path`` lie below one of ``outer``."""
        k = self.paths.index(path) if path in self.paths else -1
        while k > 0:
            k = self.parents[k]
            if self.paths[k] == outer:
                return True
        return False

    def main_text(self, path: int | None) -> str:
        """Text in the host's path, or in the page's own best one where that holds the other or the host's has less than half its score."""
        best = self.best()
        if path is not None and best:
            own, _, score = best[0]
            host = next((s for p, _, s in best if p == path), 0.0)
            if own != path and (host < score / 2 or self._within(path, own)):
                path = own
        text = self.text_in(path) if path is not None else ""
        return text or (self.text_in(best[0][0]) if best else "")


def host_votes(pages: DataFrame) -> DataFrame:
    """(host, path): the name of each host's winning container path; ties go to the deeper path, then the larger name.

    Each page gives every path of positive score a vote, in proportion to its best one's; votes are summed per host
    and path with partial sums, so a host with a third of all pages is no single task's work.
    """

    def vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, paths, depths, votes = [], [], [], []
            for host, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                best = Page(html).best()
                for path, depth, score in best:
                    hosts.append(host)
                    paths.append(path)
                    depths.append(depth)
                    votes.append(round(1000 * score / best[0][2]))
            yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(paths, pa.int64()), pa.array(depths, pa.int64()), pa.array(votes, pa.int64())], ["host", "path", "depth", "votes"])

    counted = pages.select("host", "html").mapInArrow(vote, "host string, path long, depth long, votes long").groupBy("host", "path", "depth").agg(F.sum("votes").alias("votes"))
    return counted.groupBy("host").agg(F.max(F.struct("votes", "depth", "path"))["path"].alias("path"))


def extract(df: DataFrame, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(key, url, text, n_chars) of every page.

    A page is read with its host's winning path; where that gives nothing or less than the page
    needs (see ``Page.main_text``), with its own best path; without any text it is empty.  Null html is empty; null URLs share the empty host.
    Repeated rows repeat; an empty table gives no rows; other columns are left out.
    The table of winners is broadcast up to MAX_BROADCAST_HOSTS hosts and joined by shuffle beyond.
    """
    pages = df.select(
        F.col(key).alias("key"), F.col(url).cast("string").alias("url"), host_of(F.coalesce(F.col(url).cast("string"), F.lit(""))).alias("host"), F.coalesce(F.col(html).cast("string"), F.lit("")).alias("html")
    )
    winners = written(host_votes(pages), "host-paths")
    few = winners.limit(MAX_BROADCAST_HOSTS + 1).count() <= MAX_BROADCAST_HOSTS
    placed = pages.join(F.broadcast(winners) if few else winners, "host", "left").select("key", "url", "path", "html")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for path, html in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                texts.append(Page(html).main_text(path))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["key", "url", "text", "n_chars"])

    kind = df.schema[key].dataType.simpleString()
    out = placed.mapInArrow(read, f"key {kind}, url string, text string, n_chars long")
    return out.select(F.col("key").alias(key), F.col("url").alias(url), "text", "n_chars")


def op10_html_extract(spark, sf_dir: str) -> DataFrame:
    return extract(read_table(spark, sf_dir, "pages"))
