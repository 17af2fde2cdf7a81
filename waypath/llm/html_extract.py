"""Main text of web pages by consensus of hosts: containers voted for by their generalised path."""

from __future__ import annotations

import hashlib
import html as entities
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

# ---- fixed values: what HTML calls its elements
SKIP = frozenset("script style noscript template svg math iframe object canvas head title select option button textarea form dialog".split())
BOILER = frozenset("nav footer aside menu".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
CLOSES_P = BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend", "summary", "figcaption"}
CONTAINER = frozenset("article main section div body td".split())
#: Share of its parts' scores that a mere wrapper gets.
WRAPPED = 0.9
RAW = frozenset("script style textarea title noscript iframe".split())
#: An element of these closes an open one of its group.
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
BARRIER = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}, "option": {"select"}}
#: Words in a class or id that mark what is not the article.
JUNK = frozenset("ad ads advert adverts advertisement advertising adbox sponsor sponsored promo banner sidebar side nav navbar navigation menu breadcrumb breadcrumbs footer header masthead comment comments disqus reply replies cookie cookies consent notice notices gdpr popup modal overlay newsletter subscribe signup share sharing social related recommended recommendations widget toolbar pagination pager login search".split())
#: Words that may stand beside one of JUNK in the name of what is not the article; any other word ("related-work", "no-sidebar") makes it a name of something else.
BESIDE = frozenset("left right top bottom upper lower box boxes list lists wrap wrapper container area block inner outer site page global bar bars link links button buttons item items unit slot holder panel module section zone col column primary secondary mobile desktop google dfp x px".split())
# ----
FRAMES = frozenset(("article", "main"))
#: What bounds a paragraph, and the paragraph; the tags that list items and cells are closed among.
BOUNDS_P = frozenset("td th div article section body li p main".split())
LISTY = frozenset().union(*SIBLINGS.values(), *BARRIER.values())
#: How far a node is left out: by its name only, or for good.
NAMED, LEFT_OUT = 1, 2
#: Lists and tables within each other that an implied end tag looks through; and the length from which a path goes on from its digest.
DEEP, LONG_PATH, HASHED = 512, 1000, "#"

#: A tag without < or > in its values; possessive, so a failure costs what lies before the next of them.
_PLAIN = re.compile(r"<(/?)([A-Za-z][^\s/><]*+)((?:[^<>\"']++|\"[^\"<>]*+\"|'[^'<>]*+')*+)>")
_NAME = re.compile(r"[A-Za-z][^\s/>]*")
_STOP = re.compile(r"[>\"']")
_CLASS = re.compile(r"(?:^|\s)(class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|display\s*:\s*none|aria-hidden\s*=\s*[\"']?true", re.I)
_WORDS = re.compile(r"[A-Za-z]+")
_SPACE = re.compile(r"\s+")
_DIGITS = re.compile(r"\d+")


class Node:
    __slots__ = ("tag", "cls", "junk", "parent", "items", "path", "framed", "listy", "para")

    def __init__(self, tag, cls, junk, parent):
        self.tag, self.cls, self.junk, self.parent, self.items, self.path = tag, cls, junk, parent, [], None
        up = parent or self
        #: Whether it is or lies in an article; the nearest node, itself included, of a list or table, and the nearest that bounds a paragraph or is one.
        self.framed = tag in FRAMES or (parent is not None and parent.framed)
        self.listy = self if tag in LISTY or parent is None else up.listy
        self.para = self if tag in BOUNDS_P or parent is None else up.para


def next_tag(page: str, at: int, lone: set[str]) -> tuple | None:
    """(start, end, closing, name, attributes) of the first tag from ``at`` on; name None for comments and declarations.

    A quoted value may hold a >.  Where a quotation mark is never closed, marks of that kind
    mean nothing from there on (``lone`` keeps them), so no part of a page is read more than
    a few times.
    """
    while True:
        lt = page.find("<", at)
        if lt < 0 or lt + 1 >= len(page):
            return None
        m = _PLAIN.match(page, lt)
        if m:
            return lt, m.end(), bool(m[1]), m[2].lower(), m[3]
        c = page[lt + 1]
        if c in "!?":
            if page.startswith("<!--", lt):
                end = page.find("-->", lt + 4)
                return lt, len(page) if end < 0 else end + 3, False, None, ""
            if "]" not in lone and page.startswith("<![CDATA[", lt):
                end = page.find("]]>", lt)
                if end >= 0:
                    return lt, end + 3, False, None, ""
                lone.add("]")
            end = page.find(">", lt) + 1
            return (lt, end, False, None, "") if end else None
        closing = c == "/"
        m = _NAME.match(page, lt + 1 + closing)
        if not m:
            at = lt + 1
            continue
        k = m.end()
        while s := _STOP.search(page, k):
            k, mark = s.end(), s[0]
            if mark == ">":
                return lt, k, closing, m[0].lower(), page[m.end():k - 1]
            if mark not in lone:
                close = page.find(mark, k)
                if close < 0:
                    lone.add(mark)
                    k = m.end()  # this tag is read again without that mark
                else:
                    k = close + 1
        return None


def names_junk(value: str) -> bool:
    """Whether one of the names in a class, id or role says that this is not the article."""
    for name in value.split():
        words = {w.lower() for w in _WORDS.findall(name)}
        if words & JUNK and words <= JUNK | BESIDE:
            return True
    return False


def spare(named: list[Node], root: Node) -> None:
    """A name does not count on what holds an article, a main or a headline, nor, on a page without an article or main, on what holds half of its prose."""
    order, up, held, prose, place = [root], [-1], [False], [0], {}
    framed = False
    for i, node in enumerate(order):  # grows while it is read: parents come before their parts
        place[id(node)] = i
        framed = framed or node.tag in FRAMES
        held[i] = node.tag in ("article", "main", "h1")
        for x in node.items:
            if not isinstance(x, str):
                if x.junk != LEFT_OUT and x.tag != "a":
                    order.append(x)
                    up.append(i)
                    held.append(False)
                    prose.append(0)
            elif (k := len(x.strip())) and (node.tag == "p" or k > 80):
                prose[i] += k
    for i in range(len(order) - 1, 0, -1):
        held[up[i]] = held[up[i]] or held[i]
        prose[up[i]] += prose[i]
    for n in named:
        i = place.get(id(n))
        if i is not None and (held[i] or not framed and prose[i] and 2 * prose[i] >= prose[0]):
            n.junk = 0


def parse(page: str) -> Node:
    """A tree of Nodes and raw text pieces; missing end tags are implied the usual way."""
    root = Node("#", "", 0, None)
    named = []
    cur, at, n = root, 0, len(page)
    lone: set[str] = set()
    open_now = Counter()

    def leave(to):
        nonlocal cur
        while cur is not to:
            open_now[cur.tag] -= 1
            cur = cur.parent

    while found := next_tag(page, at, lone):
        start, end, closing, tag, attrs = found
        if start > at:
            cur.items.append(page[at:start])
        at = end
        if tag is None:
            continue
        if closing:
            if open_now[tag]:
                up = cur
                while up.tag != tag:
                    up = up.parent
                leave(up.parent)
            continue
        if tag in CLOSES_P and cur.para.tag == "p":
            leave(cur.para.parent)
        if tag in SIBLINGS:
            stop, group = BARRIER[tag], SIBLINGS[tag]
            if any(open_now[g] for g in group):
                up = cur.listy
                for _ in range(DEEP):
                    if up is root or up.tag in stop or up.tag in group:
                        break
                    up = up.parent.listy
                while up.tag in group:
                    leave(up.parent)
                    up = cur
        cls, junk = "", LEFT_OUT if tag in BOILER or tag in SKIP else 0
        if attrs:
            for key, value in _CLASS.findall(attrs):
                value = value.strip("\"'")
                if key.lower() == "class":
                    cls = ".".join(sorted({_DIGITS.sub("#", c.lower()) for c in value.split()}))
                if not junk and tag not in ("body", "html", "article", "main") and names_junk(value):
                    junk = NAMED
            if _HIDDEN.search(attrs):
                junk = LEFT_OUT
        node = Node(tag, cls, junk, cur)
        if junk == NAMED:
            named.append(node)
        cur.items.append(node)
        if tag in RAW and not attrs.rstrip().endswith("/"):
            end = re.compile(f"</{tag}\\s*>", re.I).search(page, at)
            at = end.end() if end else n
            continue
        if tag not in VOID and not (attrs.rstrip().endswith("/") and tag in ("svg", "path")):
            cur = node
            open_now[tag] += 1
    if at < n:
        cur.items.append(page[at:])
    if named:
        spare(named, root)
    return root


def generalised(node: Node) -> str:
    """Tags and classes from the top, numbers replaced; siblings are not counted."""
    todo = []
    while node.path is None and node.parent is not None:
        todo.append(node)
        node = node.parent
    path = node.path or ""
    for x in reversed(todo):
        if len(path) > LONG_PATH:
            path = HASHED + hashlib.md5(path.encode("utf-8", "surrogatepass")).hexdigest()
        path = x.path = f"{path}/{x.tag}{'.' + x.cls if x.cls else ''}"
    return path


def measured(root: Node) -> dict[str, list[float]]:
    """By path of a container: [score].  Text counts in full at the nearest container; links count against it.

    A container passes its score to the one around it: whole where that one has a headline
    or prose of its own or several good parts, less where it only wraps, so the smallest
    container around all good parts scores most.  Articles and mains are wholes: what lies
    around one gets less.  Cells without paragraphs are data and pass all they have.
    """
    scores: dict[int, list] = {}

    todo = [(root, False, None)]
    while todo:
        node, in_link, holder = todo.pop()
        if node.junk or (node.tag == "header" and not node.framed):
            continue
        if node.tag in CONTAINER:
            holder = [node, 0, 0, 0, holder, False, []]
            scores[id(node)] = holder
        in_link = in_link or node.tag == "a"
        for x in reversed(node.items):
            if isinstance(x, str):
                if holder is not None:
                    k = len(x.strip())
                    holder[2 if in_link else 1] += k
                    if k and node.tag == "p" or k > 80:
                        holder[3] += k
                    if k and node.tag == "h1":
                        holder[5] = True
            else:
                todo.append((x, in_link, holder))

    out: dict[str, list[float]] = {}
    for node, text, link, prose, outer, headline, parts in reversed(scores.values()):  # inner ones come after those around them
        good = [p for p in parts if p[0] > 0]
        whole = any(p[1] for p in good)
        share = WRAPPED if whole or not (headline or prose or len(good) > 1) else 1.0
        gain = text + prose - 3.0 * link
        inside = sum(p[0] * (1.0 if p[2] else share) for p in good)
        if node.tag in ("article", "main"):
            gain, inside, whole = 1.5 * gain, inside * (1.0 if whole else 1.5), True
        gain += inside
        if gain > 0:
            out.setdefault(generalised(node), [0.0])[0] += gain
        if outer is not None:
            outer[6].append((gain, whole, node.tag == "td" and not prose and not parts))
    return out


def best_path(root: Node) -> tuple[str, float] | None:
    """A page's own vote: the best score, of equal ones the innermost."""
    found = measured(root)
    if not found:
        return None
    path = max(found, key=lambda p: (found[p][0], p.count("/"), p))
    return path, found[path][0]


def containers(root: Node, path: str) -> list[Node]:
    """Outermost nodes of that path, outside what is left out, in page order."""
    out, todo = [], [root]
    while todo:
        node = todo.pop()
        if node.tag != "#" and generalised(node) == path:
            out.append(node)
            continue
        todo.extend(x for x in reversed(node.items) if not isinstance(x, str) and not x.junk and (path.startswith(generalised(x)) or path.startswith(HASHED) or x.path.startswith(HASHED)))
    return out


def text_of(nodes: list[Node], without: int = NAMED) -> str:
    """Blocks of text in page order, one a line."""
    blocks, line = [], []

    def flush():
        if line:
            s = _SPACE.sub(" ", entities.unescape("".join(line))).strip()
            if s:
                blocks.append(s)
            line.clear()

    for top in nodes:
        todo = [top]
        while todo:
            x = todo.pop()
            if x is None:
                flush()  # the end of a block
            elif isinstance(x, str):
                line.append(x)
            elif x.junk < without and (x.tag != "header" or x.framed):
                if x.tag in BLOCK:
                    flush()
                    todo.append(None)
                elif x.tag == "br":
                    line.append(" ")
                todo.extend(reversed(x.items))
        flush()
    return "\n".join(blocks)


def extract_one(page: str, winner: str | None = None) -> str:
    """Text at the host's winning path; where a page lacks it, at the page's own best; else of the body, with what only a name speaks against if there is nothing more."""
    root = parse(page)
    nodes = containers(root, winner) if winner else []
    text = text_of(nodes) if nodes else ""
    if not text:
        own = best_path(root)
        text = text_of(containers(root, own[0])) if own else text_of([root])
    return text or text_of([root], LEFT_OUT)


def host_of(url):
    return F.lower(F.coalesce(F.regexp_extract(url, r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


def votes(pages: DataFrame) -> DataFrame:
    """(host, path, pages, score): each page's best container path, counted by host."""

    def vote(batches):
        for b in batches:
            keep, paths, scores = [], [], []
            for i, page in enumerate(b.column(1).to_pylist()):
                own = best_path(parse(page))
                if own:
                    keep.append(i)
                    paths.append(own[0])
                    scores.append(own[1])
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(keep, pa.int64())), pa.array(paths, pa.string()), pa.array(scores, pa.float64())], ["host", "path", "score"])

    per_page = pages.select(host_of(F.col("url")).alias("host"), F.coalesce("html", F.lit("")).alias("html")).mapInArrow(vote, "host string, path string, score double")
    return per_page.groupBy("host", "path").agg(F.count(F.lit(1)).alias("pages"), F.sum(F.round("score").cast("long")).alias("score"))


def winning_paths(pages: DataFrame) -> DataFrame:
    """(host, winner): the path with most votes, then most text, then the first by name."""
    return votes(pages).groupBy("host").agg(F.max_by("path", F.struct("pages", "score", "path")).alias("winner"))


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for every page.

    Pages vote by host, the votes are summed in Spark, and each page is read again at its
    host's winning path.  Null html is empty and gives an empty text; a null url makes a
    host of its own; repeated rows give repeated results; an empty table gives none; long
    pages are read whole; other columns are ignored.  The winners are a written table with
    a row per host, which Spark broadcasts only under its own size limit.
    """
    winners = written(winning_paths(pages), "hosts")
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"), host_of(F.col("url")).alias("host"))
    joined = base.join(winners, "host", "left").select("page_id", "url", "html", "winner")

    def extract(batches):
        for b in batches:
            texts = [extract_one(p, w) for p, w in zip(b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return joined.mapInArrow(extract, "page_id long, url string, text string, n_chars long")
