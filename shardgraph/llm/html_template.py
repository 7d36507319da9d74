"""Main text of web pages by deducing each host's template from equivalence classes of tokens."""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace, slices, tidy
from shardgraph.llm.url_filter import host_and_path

#: Elements whose content is never text of a page.
RAW = ("script", "style", "noscript", "template", "textarea", "iframe", "svg", "math", "object", "canvas", "audio", "video", "title")
#: Elements that hold other parts than the article.
ASIDE = {"nav", "header", "footer", "aside", "form", "menu", "dialog", "fieldset", "head", "figure"}
#: Elements inside a line whose text is a control's, not the line's.
CONTROLS = {"button", "select"}
#: Words of class, id and role that mark other parts than the article.
ASIDE_WORDS = set(
    "ad ads advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notification alert nav navbar navigation menu breadcrumb "
    "breadcrumbs sidebar side aside widget header masthead footer foot copyright comment comments reply replies disqus discussion feedback share sharing social related recommended "
    "newsletter subscribe subscription signup login popup modal overlay pagination pager toolbar search contentinfo complementary dialog".split()
)
#: Words that make a class name a state of the page or a list of finds, not a part.
STATE_WORDS = set("has have no not non with without is are open opened closed enabled disabled allowed active on off result results".split())
#: Words that say which piece of such a part a class names ('footer-links', 'comment-list'); with any other word ('share-price') the name tells nothing.
PIECE_WORDS = set(
    "site page main box bar block list item items container wrapper wrap section area panel slot unit left right top bottom inner outer center middle global primary secondary link links post posts article "
    "articles stories news icon icons button buttons form count thread title body content entry text row col column module region zone holder group set fixed sticky first last mobile desktop".split()
)
#: Class names that say the element is the article's.
CONTENT_NAMES = set("content article post entry main story text article-body post-content entry-content article-content main-content story-body".split())
#: Share of link text from which a block, and a path over a host, is a menu.
MENU_BLOCK, MENU_PATH = 0.8, 0.5
#: Elements that hold the article.
LANDMARKS = {"article", "main"}
#: Elements that stand inside a line of text.
INLINE = set("a abbr acronym b bdi bdo big br button cite code data del dfn em font i img ins kbd label mark q s samp select small span strike strong sub sup time tt u var wbr input".split())
#: Elements without an end tag.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
#: Elements that close an open one of their kind.
SELF_CLOSING = set("p li dt dd tr td th option".split())

TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:"[^"]*"|'[^']*'|[^'">])*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>""", re.S)
HINT = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)


class Element:
    """An open element; ``holds`` once an article's landmark opened inside it."""

    __slots__ = ("name", "holds")

    def __init__(self, name: str):
        self.name, self.holds = name, False


class Block:
    """One block of text with the elements around it; ``linked`` of its characters, before white space is folded, are links."""

    __slots__ = ("around", "path", "key", "text", "linked")

    def __init__(self, around: tuple[Element, ...], text: str, linked: int):
        self.around, self.text, self.linked = around, text, min(linked, len(text))
        self.path = tuple(e.name for e in around)
        self.key = "/".join(self.path)


def _element(name: str, attributes: str) -> str:
    hints = " ".join(a or b or c for a, b, c in HINT.findall(attributes)) if attributes else ""
    return f"{name}.{hints.lower()}" if hints else name


def tokens(page: str | None) -> list[Block | str]:
    """Blocks of text and tag tokens by path, in page order, as the page writes them."""
    page = page or ""
    stack: list[Element] = []
    names: list[str] = []
    out: list[Block | str] = []
    text: list[str] = []
    linked, links, muted, mute_at = 0, 0, "", 0  # link characters of the block, open links; the inline element whose text is left out, its depth
    mutes = 0

    def flush() -> None:
        nonlocal linked
        line = " ".join(entities.unescape("".join(text)).split())
        if line:
            out.append(Block(tuple(stack), line, linked))
        text.clear()
        linked = 0

    def put(s: str) -> None:
        nonlocal linked
        if not muted:
            text.append(s)
            linked += len(s) if links else 0

    at, end = 0, len(page)
    while at < end:
        m = TOKEN.search(page, at)
        if not m:
            put(page[at:])
            break
        put(page[at : m.start()])
        at = m.end()
        name = (m[2] or m[5] or "").lower()
        if not name:
            if m[0].startswith("<![CDATA["):
                put(entities.escape(m[0][9:].removesuffix("]]>")))
            continue
        closing, attributes = (m[1] or m[4]) == "/", m[3] or m[6] or ""
        if name in INLINE:
            if name == "br":
                put(" ")
            elif name == "a":
                links = max(0, links - 1) if closing else 1
            if muted and name == muted:
                mutes += -1 if closing else 1
                muted = muted if mutes else ""
            elif not muted and not closing and name not in VOID and (name in CONTROLS or (attributes and names_aside(_element("", attributes)[1:]))):
                muted, mutes, mute_at = name, 1, len(names)
            out.append("/".join(names) + (f"</{name}" if closing else f"<{name}"))
            continue
        if name in RAW:
            if not closing and not attributes.rstrip().endswith("/"):
                shut = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>", re.I).search(page, at)
                at = shut.end() if shut else (end if name in ("script", "style", "textarea", "title") else at)
            continue
        flush()
        links = 0
        if closing:
            if name in names:
                k = len(names) - 1 - names[::-1].index(name)
                del names[k:], stack[k:]
                muted = "" if k < mute_at else muted  # never closed inside its block
                out.append("/".join(names) + f"</{name}")
            continue
        if name in SELF_CLOSING and names and names[-1] == name:
            names.pop(), stack.pop()
        out.append("/".join(names) + f"<{_element(name, attributes)}")
        if name not in VOID and not attributes.rstrip().endswith("/"):
            names.append(name)
            if name in LANDMARKS:
                for e in stack:
                    e.holds = True
            stack.append(Element(_element(name, attributes)))
    flush()
    return out


def names_aside(hints: str) -> bool:
    """Does a class, id or role name another part than the article.

    One of the names must be made of such words and of words for pieces alone. Names of a state
    ('has-sidebar', 'comments-open') and an element that also bears a name of the article do not.
    """
    names = hints.split()
    if not CONTENT_NAMES.isdisjoint(names):
        return False
    for h in names:
        words = {w for w in re.split(r"[^a-z]+", h) if len(w) > 1}
        if not ASIDE_WORDS.isdisjoint(words) and words <= ASIDE_WORDS | PIECE_WORDS and STATE_WORDS.isdisjoint(words):
            return True
    return False


def is_aside(block: Block) -> bool:
    """An element around the block is another part than the article; landmarks and what holds one never are."""
    inside = False
    for e in block.around:
        name, _, hints = e.name.partition(".")
        if name in LANDMARKS:
            inside = True
        elif not e.holds and name not in ("html", "body"):
            if name in ASIDE and not (inside and name in ("header", "figure")):
                return True
            if hints and names_aside(hints):
                return True
    return False


def _mark(s: str) -> int:
    return xxhash.xxh3_64_intdigest(s.encode("utf-8", "surrogatepass")) - (1 << 63)


def _path_mark(key: str) -> int:
    return _mark(f"2{key}")


def _token(x: Block | str) -> tuple[int, int]:
    """(kind, hash) of a token: 0 a tag by its path, 1 a whole block of text by its."""
    return (0, _mark(f"0{x}")) if isinstance(x, str) else (1, _mark(f"1{x.key}\t{x.text}"))


def occurrences(page_id: int, page: str | None) -> dict[tuple[int, int], tuple[int, int]]:
    """Token -> (count, this page's part of the occurrence vector's hash); of a path, kind 2, its characters and those of links."""
    counts: dict[str | tuple[str, str], int] = {}
    paths: dict[str, tuple[int, int]] = {}
    for x in tokens(page):
        t = x if isinstance(x, str) else (x.key, x.text)
        counts[t] = counts.get(t, 0) + 1
        if not isinstance(x, str):
            chars, linked = paths.get(x.key, (0, 0))
            paths[x.key] = chars + len(x.text), linked + x.linked
    marked = ((0, _mark(f"0{t}"), c) if isinstance(t, str) else (1, _mark(f"1{t[0]}\t{t[1]}"), c) for t, c in counts.items())
    return {(k, t): (c, _mark(f"{page_id}:{c}")) for k, t, c in marked} | {(2, _path_mark(p)): v for p, v in paths.items()}


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in slices(batches, col="html"):
        host, token, kind, count, part = [], [], [], [], []
        for h, i, page in zip(b.column("host").to_pylist(), b.column("row").to_pylist(), b.column("html").to_pylist(), strict=True):
            for (k, t), (c, v) in occurrences(i, page).items():
                host.append(h), token.append(t), kind.append(k), count.append(c), part.append(v)
        yield pa.RecordBatch.from_pydict(
            {"host": pa.array(host, pa.string()), "token": pa.array(token, pa.int64()), "kind": pa.array(kind, pa.int32()), "n": pa.array(count, pa.int64()), "part": pa.array(part, pa.int64())}
        )


def in_landmark(path: tuple[str, ...]) -> bool:
    return any(e.partition(".")[0] in LANDMARKS for e in path)


def places(page: str | None, classes: dict[int, int], frames: dict[int, int]) -> tuple[dict[int, tuple[int, int]], set[tuple[int, int]]]:
    """Token -> (least, largest) place in its class's frame, and the pairs of frames that cross.

    ``classes`` maps tokens to classes and ``frames`` classes to their number of tags. Tags of a
    class take turns: the place of a tag is its turn, that of a text the turn of the tag before it.
    Two frames nest if the instances of one hold no tag of the other between their first and last.
    """
    seen: dict[int, list[int]] = {}
    got: dict[int, tuple[int, int]] = {}
    for at, x in enumerate(tokens(page)):
        kind, token = _token(x)
        c = classes.get(token)
        if c is None:
            continue
        size, own = frames.get(c, 0), seen.setdefault(c, [])
        turn = len(own) % size if size else 0
        if kind == 0:
            own.append(at)
        low, high = got.get(token, (turn, turn))
        got[token] = min(low, turn), max(high, turn)
    wide = {c: np.array(own) for c, own in seen.items() if frames.get(c, 0) > 1 and own}

    def clear(a: int, b: int) -> bool:
        first, last = wide[a][:: frames[a]], np.append(wide[a][frames[a] - 1 :: frames[a]], wide[a][-1])[: len(wide[a][:: frames[a]])]
        return bool((np.searchsorted(wide[b], first) == np.searchsorted(wide[b], last)).all())

    names = sorted(wide)
    return got, {(a, b) for i, a in enumerate(names) for b in names[i + 1 :] if not (clear(a, b) or clear(b, a))}


def _places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (host, token, other, low, high): a token's places, or a crossing of the frames ``token`` and ``other``."""
    for b in slices(batches, col="html"):
        known: dict[str, tuple[dict, dict]] = {}
        out: dict[tuple, tuple[int, int]] = {}
        for k, h in enumerate(b.column("host").to_pylist()):
            if h not in known:
                t = b.column("template")[k].as_py()
                frames: dict[int, int] = {}
                for x in t:
                    if x["kind"] == 0:
                        frames[x["class"]] = frames.get(x["class"], 0) + 1
                known[h] = {x["token"]: x["class"] for x in t}, frames
            got, crossed = places(b.column("html")[k].as_py(), *known[h])
            for token, (low, high) in got.items():
                old = out.get((h, token, None), (low, high))
                out[h, token, None] = min(low, old[0]), max(high, old[1])
            for pair in crossed:
                out[(h, *pair)] = 0, 0
        cols = list(zip(*(key + v for key, v in out.items()), strict=True)) or [[]] * 5
        yield pa.RecordBatch.from_pydict({n: pa.array(c, pa.string() if n == "host" else pa.int64()) for n, c in zip(("host", "token", "other", "low", "high"), cols, strict=True)})


def main_text(page: str | None, template: set[int] | None = None) -> str:
    """Text left in the slots of the template, whose fixed texts ``template`` has.

    A slot goes if the lists name it as another part than the article; every other slot's text
    stays. Outside of an article's landmark a text goes that the template fixes, and so do links in
    slots that hold links for the most part; inside they stay, as articles may share passages and
    list links. Without a template (few pages), text outside of the landmark goes if there is text
    inside, and list items and cells that are links go.
    """
    rest = [b for b in tokens(page) if not isinstance(b, str) and not is_aside(b)]

    def menu(b: Block) -> bool:
        if b.linked < MENU_BLOCK * len(b.text):
            return False
        return _path_mark(b.key) in template if template is not None else not {"li", "td", "dd"}.isdisjoint(e.partition(".")[0] for e in b.path)

    if template is None:
        inside = [b for b in rest if in_landmark(b.path)]
        rest = inside or [b for b in rest if not menu(b)]
    else:
        rest = [b for b in rest if in_landmark(b.path) or not (_token(b)[1] in template or menu(b))]
    return "\n".join(b.text for b in rest)


def extract(pages: DataFrame, support: float = 0.5, least_pages: int = 8) -> DataFrame:
    """Rows (page_id, url, text, n_chars).

    Tokens are tags by their path and blocks of text by theirs. One pass counts every token of
    every page: per host and token the number of pages, and a sum over pages of hashes of
    (page, count), which is equal for tokens with equal occurrence vectors and is aggregated
    before the shuffle, so a host with a third of all pages is only partial sums. Tokens on at
    least ``support`` of a host's pages (and ``least_pages``) form equivalence classes by that sum.
    The tags of a class are its frame. A second pass checks the classes: a frame is valid if its
    tags follow each other in one order on all pages, and it nests with the larger valid frames. A
    text of a valid frame is template if it has one place in it; a text that wanders through the
    frame's slots is data. A class without a valid frame falls apart into single tokens, which are
    valid alone. The third pass drops what the template fixes and keeps the text of the slots. A
    template is bounded by the tokens of a page over ``support``; templates are joined to pages by
    host, broadcast while they are few. Slots of one path whose text is links for the most part
    over all pages of the host, and which stand on a tenth of them, are menus.

    A null or empty page gives an empty text; hosts with few pages have no template, and only the
    paths of the blocks decide. Null ids and urls pass through; repeated rows count each; other
    columns are ignored. Blocks keep page order; a block's white space becomes one blank.
    """
    ws = Workspace(pages.sparkSession, "template")
    host, _ = host_and_path(F.col("url"))
    src = pages.select("page_id", "url", host.alias("host"), F.col("html").cast("string").alias("html"))
    row = F.xxhash64("page_id", "url")
    seen = src.where("html is not null").select("host", row.alias("row"), "html").mapInArrow(tidy(_count), "host string, token bigint, kind int, n bigint, part bigint")
    sums = seen.groupBy("host", "token").agg(F.max("kind").alias("kind"), F.count("*").alias("pages"), F.sum("n").alias("n"), F.sum(F.col("part").cast("decimal(38,0)")).alias("vector"))
    n_pages = src.where("html is not null").groupBy("host").agg(F.count("*").alias("all"))
    counted = sums.join(n_pages, "host")
    counted = ws.write(counted.where((F.col("pages") >= least_pages) & (F.col("pages") >= F.col("all") * F.when(F.col("kind") == 2, 0.1).otherwise(support))), "counted")
    menus = counted.where((F.col("kind") == 2) & (F.col("vector") >= F.col("n") * MENU_PATH)).select("host", F.col("token").alias("menu"))
    frequent = ws.write(counted.where((F.col("kind") < 2) & (F.col("pages") >= F.col("all") * support) & (F.col("pages") >= least_pages)), "frequent")
    member = frequent.select("host", "token", "kind", "pages", F.xxhash64("vector").alias("class"))

    def by_host(rows: DataFrame, value, name: str) -> DataFrame:
        lists = ws.write(rows.groupBy("host").agg(F.collect_list(value).alias("template")), name)
        few = lists.agg(F.coalesce(F.sum(F.size("template")), F.lit(0))).first()[0] <= 100_000
        return F.broadcast(lists) if few else lists

    tried = by_host(member, F.struct("token", "kind", "class"), "classes")
    found = src.where("html is not null").select("host", "html").join(tried, "host").mapInArrow(tidy(_places), "host string, token bigint, other bigint, low bigint, high bigint")
    found = ws.write(found.groupBy("host", "token", "other").agg(F.min("low").alias("low"), F.max("high").alias("high")), "places")
    fixed = member.join(found.where("other is null").drop("other"), ["host", "token"]).withColumn("still", F.col("low") == F.col("high"))
    frames = fixed.where("kind = 0").groupBy("host", "class").agg(F.count("*").alias("size"), F.max("pages").alias("pages"), F.min("still").alias("valid"), F.size(F.collect_set("low")).alias("turns"))
    frames = ws.write(frames.where("valid and turns = size").select("host", "class", F.struct("size", "pages", "class").alias("rank")), "frames")
    cross = found.where("other is not null").select("host", F.explode(F.array(F.struct(F.col("token").alias("a"), F.col("other").alias("b")), F.struct(F.col("other").alias("a"), F.col("token").alias("b")))).alias("p"))
    cross = cross.select("host", "p.a", "p.b").join(frames.select("host", F.col("class").alias("a"), F.col("rank").alias("ra")), ["host", "a"]).join(frames.select("host", F.col("class").alias("b"), F.col("rank").alias("rb")), ["host", "b"])
    nested = frames.join(cross.where("ra < rb").select("host", F.col("a").alias("class")).distinct(), ["host", "class"], "left_anti").select("host", "class", F.lit(True).alias("framed"))
    fixed = fixed.join(nested, ["host", "class"], "left")
    texts_of = F.when((F.col("kind") == 1) & (F.col("still") | F.col("framed").isNull()), F.col("token"))  # hosts with tags alone keep an empty list
    fixed = fixed.select("host", texts_of.alias("fixed")).unionByName(menus.select("host", F.col("menu").alias("fixed")))
    joined = src.join(by_host(fixed, F.col("fixed"), "templates"), "host", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, col="html"):
            texts = []
            for page, t in zip(b.column("html").to_pylist(), b.column("template").to_pylist(), strict=True):
                texts.append(main_text(page, None if t is None else set(t)))
            yield pa.RecordBatch.from_pydict({"page_id": b.column("page_id"), "url": b.column("url"), "text": pa.array(texts, pa.string()), "n_chars": pa.array([len(t) for t in texts], pa.int64())})

    kind = src.schema["page_id"].dataType.simpleString()
    return joined.select("page_id", "url", "html", "template").mapInArrow(tidy(run), f"page_id {kind}, url string, text string, n_chars bigint")
