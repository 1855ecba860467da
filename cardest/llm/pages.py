"""Main text of web pages: site templates are found by counting hashed subtrees per host, and deleted.

Every page is parsed into a tree by a small tolerant tokeniser. Subtrees outside the article proper are judged by their
elements (navigation, headers, footers, forms, notices, ...); all subtrees are hashed, counted per host over all pages,
and those that recur on many pages of the host are deleted wherever they stand.
"""

from __future__ import annotations

import hashlib
import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.llm.common import stored

#: A subtree is template if it stands on at least so many pages of its host, and on such a share of them.
MIN_PAGES = 5
MIN_SHARE = 0.6
#: Templates that may be broadcast: 8 bytes and a host each; beyond, they are joined by a shuffle.
BROADCAST_TEMPLATES = 500_000

# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
DROPPED = frozenset(
    "script style template noscript iframe object embed svg canvas audio video map head title textarea nav header footer aside form button select option dialog menu noembed noframes".split()
)
BLOCKS = frozenset(
    "address article blockquote body center dd details dir div dl dt fieldset figcaption figure h1 h2 h3 h4 h5 h6 hgroup hr html li main ol p pre section summary table tbody td tfoot th thead tr ul caption".split()
)
# an open paragraph ends where one of these starts
ENDS_P = frozenset(
    "address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split()
)
#: Words in class, id or role that mark what is not the article.
MARKS = re.compile(
    r"(?:^|[\s_-])(?:ad|ads|advert|adverts|advertisement|banner|breadcrumb|breadcrumbs|comment|comments|consent|cookie|cookies|disqus|footer|header|masthead|menu|nav|navbar|navigation|newsletter|notice|pager|pagination|popup|promo|related|share|sharing|sidebar|signup|skip|social|sponsor|sponsored|subscribe|toolbar|widget)(?:$|[\s_-])"
)
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]*))?""")
_SPACE = re.compile(r"\s+")


@dataclass
class Node:
    tag: str
    attributes: dict[str, str] = field(default_factory=dict)
    children: list = field(default_factory=list)  # nodes and strings
    key: int = 0


def parse(page: str) -> Node:
    """Tree of a page. Unclosed and misplaced tags are repaired as browsers do for the common cases; nothing is lost."""
    root = Node("#page")
    stack, at = [root], 0
    low = None
    opened: Counter = Counter()  # by tag, so that an end without a beginning is passed over at once

    def shut(i: int) -> None:
        opened.subtract(x.tag for x in stack[i:])
        del stack[i:]

    while True:
        m = _TOKEN.search(page, at)
        text = page[at : m.start()] if m else page[at:]
        if text:
            stack[-1].children.append(entities.unescape(text))
        if not m:
            return root
        at = m.end()
        if m.group().startswith("<![CDATA["):
            stack[-1].children.append(m.group()[9:].removesuffix("]]>"))
        if not m[2]:
            continue
        tag = m[2].lower()
        if m[1]:
            # an end tag closes its element and all inside it, unless a block stands between an inline element and its end
            for i in range(len(stack) - 1, 0, -1) if opened[tag] else ():
                if stack[i].tag == tag:
                    shut(i)
                    break
                if tag not in BLOCKS and tag not in DROPPED and stack[i].tag in BLOCKS:
                    break
            continue
        if tag in ENDS_P:
            for i in range(len(stack) - 1, 0, -1) if opened["p"] else ():
                if stack[i].tag == "p":
                    shut(i)
                    break
                if stack[i].tag in BLOCKS:
                    break
        if tag in ("li", "dt", "dd", "tr", "td", "th", "option"):
            same = {"dt": ("dt", "dd"), "dd": ("dt", "dd"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr",)}.get(tag, (tag,))
            limit = ("ul", "ol", "dl", "table", "select", "menu") if tag != "td" and tag != "th" else ("tr", "table")
            for i in range(len(stack) - 1, 0, -1) if any(opened[x] for x in same) else ():
                if stack[i].tag in same:
                    shut(i)
                    break
                if stack[i].tag in limit:
                    break
        attributes = {}
        if m[3] and m[3].strip(" /"):
            attributes = {k.lower(): entities.unescape(v.strip("\"'")) for k, v in _ATTRIBUTE.findall(m[3])}
        node = Node(tag, attributes)
        stack[-1].children.append(node)
        if tag in RAW:
            low = low or page.lower()  # lower() of ASCII names only matters; positions are checked below
            end = low.find(f"</{tag}", at) if len(low) == len(page) else page.find(f"</{tag}", at)
            end = len(page) if end < 0 else end
            node.children.append(page[at:end])
            close = page.find(">", end)
            at = len(page) if close < 0 else close + 1
        elif tag not in VOID and not m[3].endswith("/"):
            stack.append(node)
            opened[tag] += 1


def unwanted(node: Node) -> bool:
    """By what it is: an element that never holds article text, or one marked as something else, or hidden."""
    if node.tag in DROPPED:
        return True
    a = node.attributes
    if not a or node.tag in ("html", "body", "main", "article"):
        return False
    marks = " ".join(filter(None, (a.get("class"), a.get("id"), a.get("role"), a.get("data-role"), a.get("aria-label"))))
    return "hidden" in a or a.get("aria-hidden") == "true" or "display:none" in a.get("style", "").replace(" ", "") or bool(marks and MARKS.search(marks.lower()))


def parents_first(top: Node) -> list[Node]:
    """All elements of a subtree; without recursion, so that no depth of nesting is too much."""
    out, todo = [], [top]
    while todo:
        node = todo.pop()
        out.append(node)
        todo += [c for c in node.children if isinstance(c, Node)]
    return out


def hashed(top: Node) -> None:
    """Set ``key``, the 64-bit hash of the canonical text of its subtree, on every element."""
    for node in reversed(parents_first(top)):
        inner = "".join([f"<{c.key.to_bytes(8, 'little', signed=True).hex()}>" if isinstance(c, Node) else _SPACE.sub(" ", c).strip() for c in node.children])
        whole = f"<{node.tag}>{inner}</>"
        node.key = int.from_bytes(hashlib.blake2b(whole.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


def region(root: Node) -> list[Node]:
    """Where the article is: outermost article elements that are not comments, else main, else the body, else all."""
    for wanted in ("article", "main", "body"):
        found = _outermost(root, wanted)
        if found:
            return found
    return [root]


def _outermost(root: Node, tag: str) -> list[Node]:
    found, todo = [], [root]
    while todo:
        node = todo.pop()
        if node is not root:
            marks = f"{node.attributes.get('class', '')} {node.attributes.get('id', '')} {node.attributes.get('itemtype', '')}".lower()
            if node.tag == tag and not MARKS.search(marks) and "comment" not in marks:
                found.append(node)
                continue
            if node.tag in DROPPED or unwanted(node):
                continue
        todo += [c for c in reversed(node.children) if isinstance(c, Node)]
    return found


def blocks(nodes: list[Node], template: set[int] | None = None) -> list[str]:
    """Texts of the blocks, in page order: white space is one space, ends trimmed, empty ones left out."""
    out: list[str] = []
    piece: list[str] = []

    def flush() -> None:
        text = _SPACE.sub(" ", "".join(piece)).strip()
        if text:
            out.append(text)
        piece.clear()

    for top in nodes:
        todo: list[Node | str | None] = [top]
        while todo:
            item = todo.pop()
            if item is None:  # the end of a block
                flush()
            elif isinstance(item, str):
                piece.append(item)
            elif item.tag == "br" and item is not top:
                piece.append(" ")
            elif item is not top and (unwanted(item) or (template and item.key in template)):
                if item.tag in BLOCKS or item.tag in DROPPED:
                    flush()
            else:
                if item.tag in BLOCKS:
                    flush()
                    todo.append(None)
                todo += reversed(item.children)
        flush()
    return out


def repeated_candidates(root: Node) -> set[int]:
    """Keys of the subtrees that hold text and may be template: blocks of the region below its top."""
    keys: set[int] = set()
    for top in region(root):
        holds: set[int] = set()  # elements with text in them, by identity
        for node in reversed(parents_first(top)):
            if any(id(c) in holds if isinstance(c, Node) else c.strip() for c in node.children):
                holds.add(id(node))
                if node.tag in BLOCKS and node.tag not in ("html", "body", "main", "article"):
                    keys.add(node.key)
    return keys


HOST = r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)"


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page: its article's blocks, joined by line ends.

    Templates are the subtrees on at least ``min_pages`` pages and ``min_share`` of the pages of a host. A page that is itself
    a copy of others is no reason to delete its article: copies of one page count once. Null or empty html gives an empty
    text; a null url is a host of its own, as is one that names none. Repeated identifiers pass through; other columns are
    not read; an empty table gives an empty result.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    host = F.coalesce(F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), HOST, 1)), F.lit(""))
    rows = rows.withColumn("host", host)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            hosts, keys, wholes = [], [], []
            for h, page in zip(b["host"], b["html"], strict=True):
                root = parse(page or "")
                hashed(root)
                regions = region(root)
                whole = int.from_bytes(hashlib.blake2b(repr([n.key for n in regions]).encode(), digest_size=8).digest(), "little", signed=True)
                found = repeated_candidates(root)
                keys += [whole, *found]
                wholes += [whole] * (len(found) + 1)
                hosts += [h] * (len(found) + 1)
            yield pd.DataFrame({"host": hosts, "key": keys, "whole": wholes})

    seen = rows.select("host", "html").mapInPandas(count, "host string, key bigint, whole bigint")
    # distinct pages per key: a page's own key is there once per page, copies of a page have equal keys
    counts = seen.groupBy("host", "key", "whole").agg(F.lit(1).alias("one")).groupBy("host", "key").agg(F.count("*").alias("distinct_pages"), F.max(F.col("key") == F.col("whole")).alias("is_page"))
    counts = stored(counts, "page-subtrees")
    totals = counts.where("is_page").groupBy("host").agg(F.count("*").alias("pages"))
    template = counts.where(f"not is_page and distinct_pages >= {min_pages}").join(totals, "host").where(F.col("distinct_pages") >= F.lit(min_share) * F.col("pages")).select("host", "key")
    template = stored(template, "page-templates")
    if template.count() <= BROADCAST_TEMPLATES:
        known: dict[str, set[int]] = {}
        for r in template.toLocalIterator():
            known.setdefault(r["host"], set()).add(r["key"])
        shared = pages.sparkSession.sparkContext.broadcast(known)
        work = rows.select("page_id", "url", "html", "host", F.lit(None).cast("array<bigint>").alias("keys"))
    else:
        shared = None
        keys = template.groupBy("host").agg(F.collect_list("key").alias("keys"))
        work = rows.join(keys, "host", "left").select("page_id", "url", "html", "host", "keys")

    def main_text(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            texts = []
            for h, page, keys in zip(b["host"], b["html"], b["keys"], strict=True):
                root = parse(page or "")
                drop = shared.value.get(h) if shared else (set(keys) if keys is not None else None)
                if drop:
                    hashed(root)
                texts.append("\n".join(blocks(region(root), drop)))
            yield pd.DataFrame({"page_id": b["page_id"].astype("Int64"), "url": b["url"], "text": texts, "n_chars": list(map(len, texts))})

    return work.mapInPandas(main_text, "page_id bigint, url string, text string, n_chars bigint")
