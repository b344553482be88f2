"""Main text of web pages by consensus paths of their hosts.

Pass 1 cuts each page into blocks, scores its containers and names the best one by
its generalised path (tags with their classes, digits removed; a chained digest of
the whole path, however deep). A container without the main heading gives way to its
parent if that has it. Spark adds the votes up by host and path; a host keeps its few
strongest paths, those of at least a tenth of the strongest one's votes. Pass 2 cuts
each page again and takes the host's strongest path there that holds at least a quarter
of the text of the page's own best container, else the latter. If that one is among
its host's paths too, only stronger paths inside it go before it.

Hidden elements, form controls and boilerplate blocks are left out. An inline element
is left out by its class only where it is not part of a paragraph, heading or
item, and never cuts the block around it.

A host with a third of all pages is counted by partial sums, and its pages are not
moved: paths of hosts are joined by broadcast if their measured size allows, else by
a join that adaptive execution can split.

Defined results: null or empty html gives an empty text; markup may be unclosed or
damaged; an empty or unreadable host is a host of its own; repeated rows and ties
(larger vote, then smaller path) have one result.
"""

from __future__ import annotations

import re
from hashlib import blake2b
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .durable import stored
from .wordhash import portions

PATHS, LEAST_VOTES, BROADCAST_BYTES = 4, 0.1, 8 << 20

# Tags by their part in a page.
_RAW = frozenset("script style noscript template svg math iframe object canvas audio video select textarea title head".split())
_OUTSIDE = frozenset("nav footer aside form dialog menu button header label legend option optgroup datalist output progress meter".split())
_BLOCKS = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_ENDS_P = _BLOCKS - {"body", "html"}
_LEAVES = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd pre td th blockquote figcaption summary caption address tr thead tbody tfoot table ul ol dl hgroup".split())
_NOISE = re.compile(
    r"(?:^|[-_ ])(?:ad|ads|advert\w*|adbox|adslot|banner|sponsor\w*|promo\w*|menu|nav|navbar|navigation|breadcrumbs?|sidebar|side|aside|footer|foot|header|masthead|comments?|commentlist|disqus|respond|replies|reply|cookies?|consent|gdpr|notice|alert|popup|modal|overlay|newsletter|subscribe|signup|login|share|sharing|social|related|recommend\w*|widget|toolbar|pagination|pager|tags|hidden|skip)(?:$|[-_ ])"
)
_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert menu menubar form".split())
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
_DIGITS = re.compile(r"\d+")


class _Node:
    __slots__ = ("tag", "path", "out", "raw", "depth", "main", "heading")

    def __init__(self, tag, path, out, depth, main):
        self.tag, self.path, self.out, self.depth, self.main = tag, path, out, depth, main


def blocks(html: str):
    """The page's blocks outside boilerplate: (text, link characters, containers from
    the outermost to the innermost as (path, number of the container, tag))."""
    stack = [_Node("", "", False, 0, False)]
    numbers, found, parts, links, in_link, serial, at = [0], [], [], 0, 0, 0, 0

    def flush():
        nonlocal links
        if parts:
            text = " ".join(unescape("".join(parts)).split())
            parts.clear()
            if text:
                found.append((text, min(links, len(text)), tuple((n.path, k, n.tag) for n, k in zip(stack[1:], numbers[1:]))))
        links = 0

    n = len(html)
    while at < n:
        lt = html.find("<", at)
        if lt < 0:
            lt = n
        if lt > at and not stack[-1].out:
            parts.append(html[at:lt])
            links += (lt - at) if in_link else 0
        if lt >= n:
            break
        m = _TOKEN.match(html, lt)
        if m is None:
            if not stack[-1].out:
                parts.append("<")
            at = lt + 1
            continue
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            if html.startswith("<![CDATA[", lt) and not stack[-1].out:
                parts.append(html[lt + 9 : at - 3].replace("&", "&amp;"))
            continue
        closing, attributes = bool(m[1] or m[4]), m[3] or m[6] or ""
        if closing:
            if tag == "a":
                in_link = max(0, in_link - 1)
            elif tag == "p" and not any(x.tag == "p" for x in stack):
                flush()
            elif tag in _BLOCKS or any(x.tag == tag for x in stack[1:]):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i].tag == tag:
                        if tag in _BLOCKS or any(x.tag in _BLOCKS for x in stack[i:]):  # an inline element cuts no block
                            flush()
                        del stack[i:], numbers[i:]
                        break
            continue
        if tag in _RAW and tag != "head":
            if not attributes.endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}[\s/>]", re.I).search(html, at)
                if end:
                    close = html.find(">", end.start())
                    at = close + 1 if close >= 0 else n
                elif tag in ("script", "style", "textarea", "title", "template", "noscript", "iframe"):
                    at = n
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag == "a":
            in_link += 1
            continue
        if tag not in _BLOCKS and tag != "head":
            if tag in _VOID:
                continue
            in_leaf = stack[-1].tag in _LEAVES or stack[-1].tag not in _BLOCKS
            noisy = tag in _OUTSIDE or bool(attributes) and (_hidden(attributes) if in_leaf else _noisy(tag, attributes))
            if noisy and not attributes.endswith("/"):
                serial += 1
                stack.append(_Node(tag, stack[-1].path, True, len(stack), stack[-1].main))
                numbers.append(serial)
            elif tag in (x.tag for x in stack[1:] if x.out):  # a like tag inside a hidden one
                stack.append(_Node(tag, stack[-1].path, True, len(stack), stack[-1].main))
                numbers.append(serial)
            continue
        flush()
        if tag == "hr":
            continue
        if tag == "body":
            in_link = 0
            while len(stack) > 1 and stack[-1].tag == "head":
                stack.pop(), numbers.pop()
        _imply_ends(stack, numbers, tag)
        up = stack[-1]
        main = up.main or tag in ("article", "main")
        classes, noisy = _names(tag, attributes)
        out = up.out or tag == "head" or noisy or (tag in _OUTSIDE and not (tag == "header" and up.main))
        serial += 1
        stack.append(_Node(tag, blake2b(f"{up.path}/{tag}{classes}".encode("utf-8", "surrogatepass"), digest_size=12).hexdigest(), out, len(stack), main))
        numbers.append(serial)
    flush()
    return found


def _imply_ends(stack, numbers, tag):
    """Close what a new block ends without a closing tag."""

    def close(i):
        del stack[i:], numbers[i:]

    for i in range(len(stack) - 1, 0, -1):
        t = stack[i].tag
        if t == "p" and tag in _ENDS_P:
            close(i)
            break
        if t == tag == "li" or t in ("dt", "dd") and tag in ("dt", "dd") or t in ("td", "th") and tag in ("td", "th", "tr") or t == tag == "tr":
            close(i)
            if t in ("td", "th") and tag == "tr" and stack[-1].tag == "tr":
                close(len(stack) - 1)
            break
        if t in ("h1", "h2", "h3", "h4", "h5", "h6") and tag in ("p", "div", "article", "section", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol"):
            close(i)
            break
        if t not in ("p", "li", "td", "th", "dt", "dd", "tr") or tag not in ("li", "dt", "dd", "td", "th", "tr"):
            break


def _values(attributes):
    out = {}
    for m in _ATTRIBUTE.finditer(attributes):
        out.setdefault(m[1].lower(), m[2] or m[3] or m[4] or "")
    return out


def _hidden(attributes):
    values = _values(attributes)
    return values.get("role", "").lower() in _ROLES or "hidden" in values or values.get("aria-hidden") == "true" or "display:none" in values.get("style", "").replace(" ", "").lower()


def _noisy(tag, attributes):
    if _hidden(attributes):
        return True
    if tag in ("body", "html", "article", "main", "h1"):
        return False
    values = _values(attributes)
    return bool(_NOISE.search(values.get("class", "").lower()) or _NOISE.search(values.get("id", "").lower()))


def _names(tag, attributes):
    if not attributes.strip():
        return "", False
    words = sorted({_DIGITS.sub("", w) for w in _values(attributes).get("class", "").lower().split()} - {""})
    return "".join("." + w for w in words), _noisy(tag, attributes)


def container_scores(found):
    """Score of each container: path -> largest score of a container with it."""
    score, paths = {}, {}
    for text, links, chain in found:
        weight = max(0.0, len(text) - 2.0 * links) + min(text.count(",") + text.count(". "), 20)
        holders = [c for c in chain if c[2] not in _LEAVES] or list(chain[:1])
        for up, (path, number, tag) in enumerate(reversed(holders)):
            bonus = 3.0 if tag in ("article", "main") else 1.0
            score[number] = score.get(number, 0.0) + weight * bonus * (1.0, 0.75, 0.5, 0.4)[min(up, 3)]
            paths[number] = path
    best = {}
    for number, value in score.items():
        best[paths[number]] = max(best.get(paths[number], 0.0), value)
    return best


def best_path(found):
    """(path, score) of the page's best container, None if it has none. While the container lacks
    a main heading that its parent has, the parent stands for it."""
    best = container_scores(found)
    if not best:
        return None
    path, score = min(best.items(), key=lambda x: (-x[1], x[0]))
    headed = [chain for _, _, chain in found if any(tag == "h1" for _, _, tag in chain)]
    while headed and not any(p == path for chain in headed for p, _, _ in chain):
        up = {(chain[i - 1][0], chain[i - 1][2]) for _, _, chain in found for i in range(1, len(chain)) if chain[i][0] == path}
        if len(up) != 1 or (parent := up.pop())[1] in ("body", "html"):
            break
        path = parent[0]
        if any(p == path for chain in headed for p, _, _ in chain):
            return path, score
    else:
        return path, score
    return min(best.items(), key=lambda x: (-x[1], x[0]))


def text_at(found, path):
    """Text of the blocks below the containers with ``path``."""
    return "\n\n".join(text for text, _, chain in found if any(p == path for p, _, _ in chain))


def main_text(html: str | None, paths=()) -> str:
    """Text of the first of the host's ``paths`` (strongest first) that holds a quarter of as much text
    as the page's own best container, else of that one. If the host knows that one too, only
    stronger paths inside it go before it."""
    found = blocks(html or "")
    own = best_path(found)
    if own is None:
        return "\n\n".join(x[0] for x in found)
    mine = text_at(found, own[0])
    for path in paths or ():
        if path == own[0]:
            break
        inside = any(own[0] in (p for p, _, _ in chain) for _, _, chain in found if any(p == path for p, _, _ in chain))
        text = text_at(found, path) if inside or own[0] not in paths else ""
        if len(text) * 4 >= len(mine) and text:  # a winning path that holds a side piece only is no main text here
            return text
    return mine


def host_of(url):
    """Host of a url column in lower case; empty if there is none."""
    return F.lower(F.regexp_extract(F.coalesce(url.cast("string"), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def host_paths(pages: DataFrame, keep: int = PATHS) -> DataFrame:
    """host, paths (strongest first): the consensus of the best containers of its pages."""

    def vote(batches):
        for batch in portions(batches, "html"):
            out = []
            for host, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                best = best_path(blocks(html or ""))
                if best is not None:
                    out.append((host, best[0], best[1] / (best[1] + 500.0)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out)], names=["host", "path", "vote"])

    votes = pages.select(host_of(F.col("url")).alias("host"), F.col("html").cast("string").alias("html")).mapInArrow(vote, "host string, path string, vote double")
    # Rounded sums do not depend on the order of rows.
    sums = votes.groupBy("host", "path").agg(F.round(F.sum("vote"), 3).alias("votes"))
    own = Window.partitionBy("host")
    place = F.row_number().over(own.orderBy(F.desc("votes"), "path"))
    top = sums.withColumn("place", place).where(F.col("place") <= keep)
    top = top.withColumn("most", F.max("votes").over(own)).where(F.col("votes") >= F.lit(LEAST_VOTES) * F.col("most"))
    return top.groupBy("host").agg(F.transform(F.array_sort(F.collect_list(F.struct("place", "path"))), lambda x: x["path"]).alias("paths"))


def extract(pages: DataFrame, keep: int = PATHS) -> DataFrame:
    """page_id, url, text, n_chars, host for every row of ``pages``."""
    winners = stored(host_paths(pages, keep), "host-paths")
    size = winners.agg(F.coalesce(F.sum(F.octet_length("host") + 64 + F.octet_length(F.concat_ws("", "paths"))), F.lit(0))).first()[0]
    if size <= BROADCAST_BYTES:
        winners = F.broadcast(winners)

    def take(batches):
        for batch in portions(batches, "html"):
            ids, urls, htmls, paths, hosts = batch.columns
            texts = [main_text(h, p) for h, p in zip(htmls.to_pylist(), paths.to_pylist())]
            yield pa.RecordBatch.from_arrays([ids, urls, pa.array(texts, type=pa.string()), pa.array(list(map(len, texts)), type=pa.int64()), hosts], names=["page_id", "url", "text", "n_chars", "host"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    rows = rows.withColumn("host", host_of(F.col("url"))).join(winners, "host", "left")
    return rows.select("page_id", "url", "html", "paths", "host").mapInArrow(take, "page_id long, url string, text string, n_chars long, host string")
