"""Main text of web pages by inferred wrappers (operator 1).

For every host a wrapper is inferred: a union-free regular expression over the tokens of
its pages.  A page is first folded onto itself (neighbouring equal groups become one
repeated group), then aligned with the host's wrapper so far: equal tags match, differing
texts become slots, groups that only one side has become optional.  Alignment is
mergeable, so each task keeps one wrapper per host and the partial wrappers of a host
are aligned with each other in two steps; all pages take part and a host with a third of
all pages is many small inputs.

The wrapper says where a host's pages carry their text: the group with the marked article,
or else the one that holds most of the text that varies (its slots; texts that never vary
are the host's own furniture and count only where nothing varies).  Extraction walks each
whole page, keeps the text below that group, and drops menus, headers, footers, sidebars, notices, adverts, forms, scripts,
styles and reader comments by tag, role and class.  A page without that group is treated
by its own one-page wrapper.

Defined results for odd rows: null and empty html give an empty text; a null url is a
host of its own; broken markup is read as far as it goes (unclosed elements end with
their parent); text without any tag is the text; repeated pages are extracted each; an
empty table gives an empty result.  Extra columns are ignored.
"""

from __future__ import annotations

import bisect
import html as entities
import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, ship

#: Hosts that a task keeps before it hands on its partial wrappers; bytes of paths that may be broadcast.
HOSTS, BROADCAST = 2_000, 16 << 20
#: Longest repeated group; deepest nesting that is told apart.
GROUP, DEPTH = 3, 200

#: Element and class names: fixed values.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
RAW = set("script style textarea title noscript iframe template xmp".split())
BLOCK = set(
    "html body address article aside blockquote canvas center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hr li main nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
DROPPED = set("head nav header footer aside form script style noscript template iframe svg canvas button select option input textarea object embed dialog menu".split())
NOISE = set(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner sidebar side menu nav navbar navigation breadcrumb breadcrumbs "
    "footer header masthead topbar comment comments commentlist disqus replies reply cookie cookies consent gdpr notice notices notification alert popup modal overlay "
    "share sharing social related recommended newsletter subscribe signup login widget widgets pagination pager toolbar skip copyright".split()
)
ROLES = set("navigation banner contentinfo complementary search dialog alert menu menubar toolbar".split())
MAIN = set("article main".split())
CONTENT = set("content article post entry story main articlebody body".split())
#: Which open elements a new one closes.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tr", "td", "th"}, "tfoot": {"tbody", "tr", "td", "th"}}
HOLDERS = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}, "thead": {"table"}, "tbody": {"table"}, "tfoot": {"table"}}

TAG = re.compile(r"</?([a-zA-Z][^\s/>]*)")
#: What follows a tag's name: quotes count after an equals sign.  Possessive, so it never goes back.
INSIDE = re.compile(r"(?>[^>=]*+(?:=\s*+(?>\"[^\"]*+\"|'[^']*+'|)[^>=]*+)*+)>")
RAW_END = {name: re.compile(rf"</{name}[\s>/]", re.I) for name in RAW}
ATTRIBUTE = re.compile(r"\b(class|id|role|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
WORD = re.compile(r"[a-z]+")


class Node:
    """An element or, with name ``#``, a text."""

    __slots__ = ("children", "label", "name", "noise", "text")

    def __init__(self, name: str, label: str = "", noise: bool = False, text: str = "") -> None:
        self.name, self.label, self.noise, self.text, self.children = name, label or name, noise, text, []


_seen: dict[tuple[str, str], tuple[str, bool]] = {}


def _describe(name: str, attributes: str) -> tuple[str, bool]:
    """(label, is noise) of an element; the label is the token that alignment compares."""
    held = _seen.get((name, attributes))
    if held is None:
        found = {k.lower(): a or b or c for k, a, b, c in ATTRIBUTE.findall(attributes)} if attributes else {}
        words = set(WORD.findall(re.sub(r"([a-z])([A-Z])", r"\1 \2", found.get("class", "") + " " + found.get("id", "")).lower()))
        role = found.get("role", "").lower()
        noise = name in DROPPED or role in ROLES or (name not in MAIN and name not in ("html", "body") and bool(words & NOISE))
        main = name in MAIN or role in ("main", "article") or "articlebody" in found.get("itemprop", "").lower() or (name in ("div", "section", "td") and bool(words & CONTENT) and not noise)
        mark = re.sub(r"\d+", "9", (found.get("class") or found.get("id") or "").split(" ")[0])
        held = (name + ("." + mark if mark else "") + ("!" if main else ""), noise)
        if len(_seen) > 10_000:
            _seen.clear()
        if len(attributes) < 1_000:
            _seen[name, attributes] = held
    return held


def tags(page: str) -> Iterator[tuple[str, str | None, str, int]]:
    """(text before, name or None, attributes, end) of each tag; a closing tag's name begins with ``/``.

    The consumer may send back a position to go on from.  Every character is looked at a
    bounded number of times: once a tag turns out not to end outside quotes, quotes no
    longer count on this page.
    """
    start = at = 0
    quotes = True
    while True:
        low = page.find("<", at)
        if low < 0:
            yield page[start:], None, "", len(page)
            return
        follows = page[low + 1 : low + 2]
        if follows == "!" or follows == "?":
            mark = "-->" if page.startswith("<!--", low) else ">"
            end = page.find(mark, low + 2)
            name, attributes, end = None, "", len(page) if end < 0 else end + len(mark)
        else:
            hit = TAG.match(page, low)
            if hit is None:
                at = low + 1
                continue
            inside = INSIDE.match(page, hit.end()) if quotes else None
            quotes = inside is not None
            end = inside.end() if inside else page.find(">", hit.end()) + 1
            if not end:
                yield page[start:low], None, "", len(page)
                return
            name, attributes = ("/" if follows == "/" else "") + hit[1].lower(), page[hit.end() : end - 1]
        again = yield page[start:low], name, attributes, end
        start = at = end if again is None else again


def parse(page: str) -> Node:
    """A tolerant element tree of a page."""
    root = Node("#root")
    stack = [root]
    flat: Counter = Counter()  # open elements below DEPTH, which are not on the stack
    found, again = tags(page), None
    while True:
        try:
            piece, name, attributes, at = found.send(again)
        except StopIteration:
            return root
        again = None
        if piece:
            stack[-1].children.append(Node("#", text=entities.unescape(piece) if "&" in piece else piece))
        if name is None:
            continue
        if name[0] == "/":
            name = name[1:]
            if flat[name]:
                flat[name] -= 1
                continue
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].name == name:
                    del stack[k:]
                    flat.clear()
                    break
                if stack[k].name in ("table", "article", "body") and name not in BLOCK:
                    break
            continue
        if name in BLOCK:
            for k in range(len(stack) - 1, 0, -1):  # a block ends an open paragraph
                if stack[k].name == "p":
                    del stack[k:]
                    break
                if stack[k].name in BLOCK:
                    break
        if name in CLOSES:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].name in HOLDERS[name]:
                    break
                if stack[k].name in CLOSES[name]:
                    del stack[k:]
        label, noise = _describe(name, attributes)
        node = Node(name, label, noise)
        stack[-1].children.append(node)
        if name in RAW:
            end = RAW_END[name].search(page, at)
            if end is None:
                return root
            if name not in DROPPED and name != "title":
                node.children.append(Node("#", text=entities.unescape(page[at : end.start()])))
            again = page.find(">", end.start()) + 1 or len(page)
        elif name not in VOID and not attributes.endswith("/"):
            if len(stack) < DEPTH or (noise and not stack[-1].noise):
                stack.append(node)
            else:
                flat[name] += 1


# A wrapper item is [label, quantifier, children, constant, mass]: quantifier "", "?", "+"
# or "*"; constant is the checksum of a text that has not varied, None for a slot or tag;
# mass is the number of text characters seen below.


def fold(node: Node) -> list:
    """The page's own expression: its element, with neighbouring equal groups folded."""
    if node.name == "#":
        words = node.text.strip()
        return ["#", "", [], zlib.crc32(words.encode("utf-8", "replace")), len(words)]
    kids = [fold(c) for c in node.children if c.name != "#" or c.text.strip()]
    kids = repeated(kids)
    mass = 0 if node.noise else sum(k[4] for k in kids)
    return [node.label + ("~" if node.noise else ""), "", kids, None, mass]


def repeated(items: list) -> list:
    """Neighbouring equal groups of up to GROUP tokens become one repeated group."""
    out: list = []
    for item in items:
        out.append(item)
        for width in range(1, GROUP + 1):
            if len(out) >= 2 * width and [x[0] for x in out[-width:]] == [x[0] for x in out[-2 * width : -width]]:
                if width == 1 and out[-1][0] == "#":
                    break
                for k in range(width):
                    out[-2 * width + k] = merge(out[-2 * width + k], out[-width + k], again=True)
                del out[-width:]
                break
    return out


_UNION = {("", ""): "", ("", "?"): "?", ("", "+"): "+", ("", "*"): "*", ("?", "?"): "?", ("+", "?"): "*", ("*", "?"): "*", ("+", "+"): "+", ("*", "+"): "*", ("*", "*"): "*"}


def merge(a: list, b: list, again: bool = False) -> list:
    """Align two items of one label; ``again``: b follows a, so the group repeats."""
    quantifier = _UNION[tuple(sorted((a[1], b[1])))]
    if again:
        quantifier = "*" if a[1] in "?*" and a[1] and b[1] in "?*" and b[1] else "+"
    constant = a[3] if a[3] == b[3] else None
    return [a[0], quantifier, align(a[2], b[2]), constant, a[4] + b[4]]


def optional(item: list) -> list:
    return [item[0], "*" if item[1] in ("+", "*") else "?", *item[2:]]


def align(a: list, b: list) -> list:
    """Align two token sequences; what only one of them has becomes optional.

    Ends that agree are matched first.  At a mismatch each side's next token is looked up
    in the other; the nearer of the two is where the sequences go on together, and what
    lies before it is optional.
    """
    x, y = [i[0] for i in a], [i[0] for i in b]
    if x == y:
        return [merge(p, q) for p, q in zip(a, b, strict=True)]
    n, m = len(a), len(b)
    tail = 0
    while tail < min(n, m) and x[n - 1 - tail] == y[m - 1 - tail]:
        tail += 1
    n, m = n - tail, m - tail
    places: tuple[dict, dict] = ({}, {})
    for labels, size, held in ((x, n, places[0]), (y, m, places[1])):
        for k in range(size):
            held.setdefault(labels[k], []).append(k)

    def ahead(held: dict, label: str, at: int) -> int | None:
        own = held.get(label, ())
        k = bisect.bisect_left(own, at)
        return own[k] if k < len(own) else None

    out, i, j = [], 0, 0
    while i < n and j < m:
        if x[i] == y[j]:
            out.append(merge(a[i], b[j]))
            i, j = i + 1, j + 1
            continue
        p, q = ahead(places[0], y[j], i), ahead(places[1], x[i], j)
        if p is None and q is None:
            out += [optional(a[i]), optional(b[j])]
            i, j = i + 1, j + 1
        elif q is None or (p is not None and p - i <= q - j):
            out += map(optional, a[i:p])
            i = p
        else:
            out += map(optional, b[j:q])
            j = q
    out += map(optional, a[i:n] + b[j:m])
    out += [merge(p, q) for p, q in zip(a[n:], b[m:], strict=True)]
    return repeated(out)


def expression(item: list) -> str:
    """The wrapper as text, e.g. ``article(h1(#)p(#)+)``; constants are quoted checksums."""
    inner = "".join(map(expression, item[2]))
    word = "#" if item[0] == "#" and item[3] is None else f"'{item[3]}'" if item[0] == "#" else item[0]
    return word + (f"({inner})" if inner else "") + item[1]


def varying(item: list, held: dict[int, int]) -> int:
    """Characters of text below an item that are slots, noise left out; noted by item in ``held``."""
    own = item[4] * (item[3] is None) if item[0] == "#" else sum(varying(k, held) for k in item[2])
    held[id(item)] = 0 if item[0].endswith("~") else own
    return held[id(item)]


def region(wrapper: list) -> list[str]:
    """Labels from the top down to the group that carries the text.

    A marked main element with the most text wins (the outermost of nested ones);
    otherwise the walk goes down as long as one child holds most of the varying text.
    """
    slots: dict[int, int] = {}
    mass = (lambda k: slots[id(k)]) if varying(wrapper, slots) else (lambda k: k[4])
    found: list[tuple[int, list[str]]] = []
    todo = [(wrapper, [wrapper[0]])]
    while todo:
        item, path = todo.pop()
        if item[0].endswith("~"):
            continue
        if item[0].split(".")[0].rstrip("!") in MAIN or item[0].endswith("!"):
            strong = item[0].split(".")[0].rstrip("!") in MAIN
            found.append((mass(item) * (4 if strong else 1), path))
            if strong:
                continue
        todo += [(k, [*path, k[0]]) for k in item[2]]
    found = [f for f in found if f[0] * 2 >= mass(wrapper)]
    if found:
        return max(found, key=lambda f: (f[0], -len(f[1])))[1]
    path, item = [wrapper[0]], wrapper
    while True:
        heavy = [k for k in item[2] if k[0] != "#" and not k[0].endswith("~") and mass(k) * 10 >= mass(item) * 7 and k[1] in ("", "?")]
        if not heavy or heavy[0][0].split(".")[0] in ("p", "li", "td", "h1", "h2", "h3", "pre", "span", "b", "i", "a", "em", "strong", "blockquote"):
            return path
        item = heavy[0]
        path.append(item[0])


def _below(node: Node, path: list[str]) -> list[Node]:
    """The elements that a path of labels leads to, in page order."""
    here = [node]
    for label in path[1:]:
        here = [c for n in here for c in n.children if c.label == label and not c.noise]
    return here


def visible(node: Node, out: list[str]) -> None:
    """Text pieces below a node, with a blank at the borders of blocks."""
    todo: list = [node]
    while todo:
        node = todo.pop()
        if isinstance(node, str):
            out.append(node)
        elif node.name == "#":
            out.append(node.text)
        elif not node.noise:
            edge = node.name in BLOCK or node.name == "br"
            if edge:
                out.append(" ")
                todo.append(" ")
            todo.extend(reversed(node.children))


def main_text(page: str | None, path: list[str]) -> str:
    if not page:
        return ""
    tree = parse(page)
    found = _below(tree, path) if len(path) > 1 else []
    if not found:
        found = _below(tree, region(fold(tree)))
    pieces: list[str] = []
    for node in found:
        visible(node, pieces)
        pieces.append(" ")
    return " ".join("".join(pieces).split())


def _wrapper_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: dict[str, list] = {}

    def emit() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array([json.dumps(w) for w in held.values()], pa.string())], names=["host", "wrapper"])

    for batch in batches:
        for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if page:
                own = fold(parse(page))
                held[host] = merge(held[host], own) if host in held else own
                if len(held) > HOSTS:
                    yield emit()
                    held.clear()
    yield emit()


def _merge_group(key: tuple, table: pa.Table) -> pa.Table:
    every = [json.loads(w) for w in sorted(table.column("wrapper").to_pylist())]  # whatever the order of arrival
    whole = every[0]
    for other in every[1:]:
        whole = merge(whole, other)
    return pa.table({"host": [key[0].as_py()], "wrapper": [json.dumps(whole)]}, schema=pa.schema([("host", pa.string()), ("wrapper", pa.string())]))


def with_host(pages: DataFrame) -> DataFrame:
    url = F.coalesce(F.col("url").cast("string"), F.lit(""))
    return pages.withColumn("_host", F.lower(F.regexp_extract(url, r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1)))


def infer(pages: DataFrame) -> DataFrame:
    """(host, wrapper) for every host, the wrapper as JSON; from all pages of the host."""
    schema = "host string, wrapper string"
    partial = with_host(pages).select("_host", F.col("html").cast("string").alias("html")).mapInArrow(_wrapper_batches, schema)
    partial = materialise(partial)
    salted = partial.groupBy("host", F.pmod(F.xxhash64("wrapper"), F.lit(32)).alias("salt")).applyInArrow(_merge_group, schema)
    return salted.groupBy("host").applyInArrow(_merge_group, schema)


def _region_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        whole = [json.loads(w) for w in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([json.dumps(region(w)) for w in whole], pa.string()), pa.array([expression(w) for w in whole], pa.string())], names=["host", "path", "expression"])


def regions(wrappers: DataFrame) -> DataFrame:
    """(host, path, expression): where the text is, and the wrapper in readable form."""
    return wrappers.mapInArrow(_region_batches, "host string, path string, expression string")


def _extract_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        paths: dict[str | None, list[str]] = {None: []}
        texts = []
        for page, path in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
            if path not in paths:
                paths[path] = json.loads(path)
            texts.append(main_text(page, paths[path]))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    found = materialise(regions(infer(pages)).select(F.col("host").alias("_host"), "path"))
    size = found.agg(F.count("*") * 64 + F.coalesce(F.sum(F.octet_length("_host") + F.octet_length("path")), F.lit(0))).first()[0]
    small = size <= BROADCAST
    rows = with_host(pages).join(F.broadcast(found) if small else found, "_host", "left")
    return rows.select("page_id", "url", "html", "path").mapInArrow(_extract_batches, "page_id long, url string, text string, n_chars long")


ship(__name__)
