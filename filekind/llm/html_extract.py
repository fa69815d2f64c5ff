"""Main text of web pages by consensus host paths.

Each page is parsed into containers and text blocks. A container's path is the chain of its tags with their generalised classes and ids
(digits become N; a tag that has neither is told by its place among its like); paths travel as 64-bit hashes. A page scores its containers by the text they hold
outside links and outside parts that are never article text, and votes for the deepest container with most of that score. Spark counts the votes
by host and path. A path whose container says the same on most of the different pages that vote for it is the host's furniture and drops out; the paths with
enough votes win, and every page of the host is extracted again with the most voted of them that it has, against its own choice. A page that has no winning path keeps to its own best container.

What never is article text is told by elements (nav, aside, footer, form parts, header outside an article, what is not shown) and by class, id or role words that name the
parts of the contract. Such a word is a hint only: a container that holds an article or main element, or nearly all of the page's text, is taken for what it holds.

Defined cases: null html is an empty page and gives empty text; a page without usable text gives empty text; hosts are cut from the URL, null or
odd URLs share the empty host; ties in votes go to the smaller hash of a path; repeated rows are extracted alike; unclosed tags,
cut-off markup, stray quotes, deep nesting and very long pages are read to their end in linear time; an empty table gives an empty result; further columns are left alone.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterable, Iterator

import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import offered, stash, table
from .url_filter import host_of

#: Attributes of a tag. A quote encloses a value only right after an equals sign; elsewhere it is a character like others.
_REST = r"""((?:[^>=]++|=\s*+"[^"]*+"|=\s*+'[^']*+'|=)*+)"""
#: A comment, declaration, or tag with its attributes; a `<` that starts none of these is text.
MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)" + _REST + r"(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"""([a-zA-Z_:][-\w:.]*+)\s*+(?:=\s*+("[^"]*+"|'[^']*+'|[^\s>]++))?""")
#: Elements whose content is not markup, with their ends.
RAW = {t: re.compile(rf"</{t}(?=[\s/>]|\Z)[^>]*+(?:>|\Z)", re.I) for t in "script style textarea title xmp iframe noembed noframes".split()}
#: Elements that are never part of an article.
NEVER = frozenset("nav footer aside dialog menu button fieldset head select datalist noscript template".split())
#: What may stand in a head; anything else begins the body.
IN_HEAD = frozenset("title meta link script style base noscript template head".split())
#: Elements that hold blocks and take part in paths.
CONTAINERS = NEVER | frozenset("html body main article section div header form ul ol dl table tbody thead tfoot tr td th li figure blockquote details center hgroup address search".split())
#: Elements that begin and end a block of text.
BLOCKS = CONTAINERS | frozenset("p h1 h2 h3 h4 h5 h6 dt dd pre hr br figcaption summary caption legend option".split())
#: What ends an open element of the left kind, if that is the innermost.
IMPLIED = {"li": {"li"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "tbody": {"tr", "td", "th", "thead", "tbody"}, "tfoot": {"tr", "td", "th", "tbody"}}
#: Words that name the parts of a page which are not its article, and words that turn a class into a remark about layout.
PARTS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo menu menus nav navbar navigation breadcrumb breadcrumbs sidebar sidebars footer masthead topbar cookie cookies consent comment comments disqus replies newsletter subscribe signup login search popup modal complementary contentinfo".split())
#: Such words where no article or main element is around: inside one they may be its own.
OUTER_PARTS = frozenset("header banner notice notices alert alerts form widget share social related".split())
REMARKS = frozenset("no not has have with without is hide show open closed content main article post page body wrapper layout".split())
#: Weight of text in article and main elements; share of a page's score that its container must hold; votes that a path needs against the host's best.
FAVOUR, SHARE, VOTES = 4, 0.7, 0.25
#: A container that holds more of a page's text than this is no part of it, whatever its name.
WRAPS = 0.9
#: A path that so many different pages vote for is furniture if they hold no more than one in SAME different texts there.
MANY, SAME = 3, 3
DIGITS = re.compile(r"\d+")
HIDDEN = re.compile(r"display\s*:\s*none", re.I)


def names_part(words: str, inside: bool) -> bool:
    """Whether a class, id or role names a part that is not article text: by its first or last syllable, unless another is a remark."""
    for word in words.split():
        parts = [x for x in re.split(r"[-_]+", word) if x]
        if parts and not REMARKS.intersection(parts) and any(x in PARTS or not inside and x in OUTER_PARTS for x in (parts[0], parts[-1])):
            return True
    return False


class Page:
    """Containers and text blocks of a page, in page order. Container 0 is the whole page."""

    def __init__(self, source: str):
        self.steps, self.paths, self.parents = [""], [0], [-1]
        self.marks = [0]  # 0: wanted, 1: named as a part, 2: an element that never is article text
        self.holds = [False]  # an article or main element is inside
        self.blocks: list[tuple[int, str, int, int]] = []  # (container, text, characters in links, weight)
        stack: list[tuple[str, int, bool]] = [("", 0, False)]  # (tag, container, inside an article)
        opened: Counter[str] = Counter()
        places: Counter[tuple[int, str]] = Counter()
        piece: list[str] = []
        link = linked = 0
        at, size = 0, len(source)

        def end_block() -> None:
            nonlocal linked
            if piece:
                if text := " ".join("".join(piece).split()):
                    self.blocks.append((stack[-1][1], text, linked, FAVOUR if stack[-1][2] else 1))
                piece.clear()
            linked = 0

        def close(to: int) -> None:
            for x in stack[to:]:
                opened[x[0]] -= 1
            del stack[to:]

        while at < size:
            m = MARKUP.search(source, at)
            to = m.start() if m else size
            if to > at:
                text = source[at:to]
                if stack[-1][0] == "head" and not text.isspace():
                    close(len(stack) - 1)
                piece.append(html.unescape(text) if "&" in text else text)
                linked += len(piece[-1]) if link else 0
            if not m:
                break
            at = m.end()
            tag = (m[2] or "").lower()
            if not tag:
                continue
            if m[1]:
                if tag == "a":
                    link = 0
                if tag in BLOCKS:
                    end_block()
                    if opened[tag]:
                        i = len(stack) - 1
                        while stack[i][0] != tag:
                            i -= 1
                        close(i)
                continue
            if tag in RAW:
                end = RAW[tag].search(source, at)
                at = end.end() if end else size
                continue
            if stack[-1][0] == "head" and tag not in IN_HEAD:
                end_block()
                close(len(stack) - 1)
            if tag == "a":
                link = 1
            if tag not in BLOCKS:
                continue
            end_block()
            if tag not in CONTAINERS:
                continue
            while tag in IMPLIED and stack[-1][0] in IMPLIED[tag]:
                close(len(stack) - 1)
            attributes = {k.lower(): v.strip("\"'") for k, v in ATTRIBUTE.findall(m[3])}
            named = " ".join(attributes.get(k, "") for k in ("class", "id", "role")).lower()
            above, inside = stack[-1][1], stack[-1][2]
            mark = self.marks[above]
            if tag in NEVER or mark == 2 or "hidden" in attributes or HIDDEN.search(attributes.get("style", "")):
                mark = 2
            elif tag not in ("html", "body", "main", "article") and (tag == "form" or tag == "header" and not inside or names_part(named, inside)):
                mark = 1
            else:
                mark = 0  # what a container above is named counts for its whole content later
            step = tag + "".join("." + c for c in sorted(DIGITS.sub("N", attributes.get("class", "").lower()).split()))
            if "id" in attributes:
                step += "#" + DIGITS.sub("N", attributes["id"].lower())
            if step == tag and tag not in ("html", "body"):
                places[above, tag] += 1
                step = f"{tag}[{places[above, tag]}]"
            article = tag in ("main", "article") or attributes.get("role", "").lower() in ("main", "article")
            self.steps.append(step)
            self.paths.append(xxhash.xxh64_intdigest(step.encode("utf-8", "surrogatepass"), self.paths[above]))
            self.parents.append(above)
            self.marks.append(mark)
            self.holds.append(article)
            opened[tag] += 1
            stack.append((tag, len(self.paths) - 1, inside or article))
        end_block()
        self.weigh()

    def summed(self, own: list[float]) -> list[float]:
        """The total of each container with all that it contains."""
        total = list(own)
        for i in range(len(total) - 1, 0, -1):
            total[self.parents[i]] += total[i]
        return total

    def weigh(self) -> None:
        """Settle what is unwanted, and the score of each container."""
        n = len(self.paths)
        for i in range(n - 1, 0, -1):
            self.holds[self.parents[i]] = self.holds[self.parents[i]] or self.holds[i]
        plain = [0.0] * n
        for c, text, linked, weight in self.blocks:
            if self.marks[c] < 2:
                plain[c] += max(0, len(text) - 2 * linked) * weight
        held = self.summed(plain)
        for trusted in (True, False):  # words that leave nothing are not believed
            self.unwanted = [False] * n
            for i in range(1, n):
                named = trusted and self.marks[i] == 1 and not self.holds[i] and held[i] <= WRAPS * held[0]
                self.unwanted[i] = self.marks[i] == 2 or named or self.unwanted[self.parents[i]]
            self.total = self.summed([0.0 if u else x for u, x in zip(self.unwanted, plain, strict=True)])
            if self.total[0]:
                break

    def best(self) -> int:
        """The deepest container with most of the page's score; 0, the whole page, if there is none deeper."""
        enough, found = SHARE * self.total[0], 0
        for i in range(1, len(self.paths)):
            if self.total[0] and self.total[i] >= enough and self.parents[i] == found:
                found = i
        return found

    def joined(self, chosen: list[bool]) -> str:
        """The wanted blocks of the chosen containers and all that they contain."""
        for i in range(1, len(chosen)):
            chosen[i] = chosen[i] or chosen[self.parents[i]]
        return " ".join(b[1] for b in self.blocks if chosen[b[0]] and not self.unwanted[b[0]])

    def own_text(self) -> str:
        top = self.best()
        return self.joined([i == top for i in range(len(self.paths))])

    def text(self, paths: Iterable[int]) -> str:
        """The blocks inside containers of the first of the given paths that holds any here, or else of the page's own best."""
        for path in paths:
            if text := self.joined([p == path for p in self.paths]):
                return text
        return self.own_text()


def hashed(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass"))


def signed(h: int) -> int:
    return h - (1 << 64) if h >= 1 << 63 else h


def votes(pages: DataFrame, html_col: str = "html", url_col: str = "url") -> DataFrame:
    """(host, path, step, votes, texts, pages): how many pages of a host choose a path, and how many different texts these hold there and in all."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in parts:
            out = []
            for host, source in zip(x["host"], x["html"], strict=True):
                page = Page(source or "")
                if page.total[0] and (top := page.best()):
                    out.append((host, signed(page.paths[top]), page.steps[top], signed(hashed(page.own_text())), signed(hashed(page.joined([True] * len(page.paths))))))
            yield pd.DataFrame(out, columns=["host", "path", "step", "said", "whole"])

    cast = pages.select(host_of(F.col(url_col)).alias("host"), F.col(html_col).alias("html")).mapInPandas(run, "host string, path long, step string, said long, whole long")
    # One row for each text first, so that neither a common host nor a common page meets in one task.
    said = cast.groupBy("host", "path", "step", "said", "whole").agg(F.count("*").alias("n"))
    return said.groupBy("host", "path", "step").agg(F.sum("n").alias("votes"), F.count_distinct("said").alias("texts"), F.count_distinct("whole").alias("pages"))


def winners(counted: DataFrame) -> DataFrame:
    """(host, paths, steps): the paths with at least VOTES of the votes that the host's best path has, furniture left out, most votes first."""
    fair = counted.where((F.col("pages") < MANY) | (F.col("texts") * SAME > F.col("pages")))
    top = fair.groupBy("host").agg(F.max("votes").alias("most"))
    won = fair.join(top, "host").where(F.col("votes") >= VOTES * F.col("most"))  # at most 1 / VOTES paths for each vote of the best
    ordered = F.sort_array(F.collect_list(F.struct((-F.col("votes")).alias("less"), "path", "step")))
    return won.groupBy("host").agg(ordered.alias("w")).select("host", F.col("w.path").alias("paths"), F.col("w.step").alias("steps"))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row for each page: page_id, url, text, n_chars, steps (the last steps of the winning paths of its host)."""
    won = stash(winners(stash(votes(pages, html_col, url_col))))

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in parts:
            x["text"] = [Page(h or "").text([int(v) % (1 << 64) for v in p] if p is not None else ()) for h, p in zip(x["html"], x["paths"], strict=True)]
            yield x[["page_id", "url", "text", "steps"]]

    kept = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host_of(F.col(url_col)).alias("host"))
    told = kept.join(offered(won), "host", "left")
    kind = pages.schema[id_col].dataType.simpleString()
    # Ids travel as text, so that a null id stays null.
    out = told.select(F.col("page_id").cast("string").alias("page_id"), "url", "html", "paths", "steps").mapInPandas(run, "page_id string, url string, text string, steps array<string>")
    return out.select(F.col("page_id").cast(kind).alias("page_id"), "url", "text", F.length("text").cast("long").alias("n_chars"), "steps")


def op4_consensus_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
