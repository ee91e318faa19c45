"""Main text of web pages by differencing each page from the one with the nearest URL.

1. A tolerant reader cuts the markup into lines, one for each block of the
   page. Its structure weighs every line: *site* (menus, page headers and
   footers, sidebars, notices, adverts, forms, reader comments), *card* (an
   article element named as a teaser of another page), *guarded* (the story: the
   longest article, or main where it has none, or the longest block named like a
   story) or *open* (all else that may be article text).
2. Pages are put in the order of host, path and id; every page is paired with
   the neighbour in its host that shares the longer part of the path. The two
   lists of lines are aligned by a longest common subsequence.
3. Site and card lines go, and so do open lines that the alignment finds
   shared. Guarded lines stay although they are shared: there, shared lines are
   text that several articles hold. A page left without text keeps its open
   lines, then its cards, since there is nothing to tell site from article.

Pairing and alignment see 64-bit hashes of lines. Pages are read a second time
for their text, which no shuffle carries while the pages that lose open lines
fit a checked broadcast.
"""

from __future__ import annotations

import bisect
import html
import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.plans.common import checked_broadcast, ordinal, written

_RAW = {"script", "style", "title", "textarea", "noscript", "template", "iframe", "svg", "math", "xmp"}
_SKIP = {"head", "nav", "footer", "aside", "form", "button", "select", "menu", "dialog", "object", "canvas", "audio", "video", "map"}
_INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q rb rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
_VOID = set("area base br col embed hr img input link meta param source track wbr".split())
# a class or id is a part of the site if its parts are all of these two lists, and one is of the first
_BAD_NAMES = set("ad ads advert adverts advertisement adsense banner sponsor sponsored promo promoted promotion cookie cookies consent gdpr notice notices alert newsletter subscribe popup modal overlay menu nav navbar navigation breadcrumb breadcrumbs sidebar widget widgets related recommended footer header masthead topbar toolbar share sharing social comment comments commentlist disqus replies reply respond pagination pager copyright".split())
_BOX_NAMES = set("area articles author bar block body bottom box buttons container count fixed form global group icons inner item items left links list main menu news page pages panel post posts primary reader right row secondary section side site slot stories sticky text thread title top user wrap wrapper unit".split())
_SITE_NAMES = {"side-bar", "skip-link", "skip-links"}
_CARD_NAMES = set("card cards teaser teasers preview previews tile tiles".split())
_BAD_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alertdialog", "alert", "menu", "menubar", "form"}
_STORY_NAMES = set("article article-body articlebody article-content post-body post-content entry entry-content story story-body".split())
_BODY_NAMES = set("main main-content maincontent content page-content post body-content".split())
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*+)(?P<attrs>(?:[^>=]++|=\s*+\"[^\"]*+\"(?=[\s/>]|\Z)|=\s*+'[^']*+'(?=[\s/>]|\Z)|=)*+)(?:>|\Z)", re.S)
_ATTR = re.compile(r"(?i)(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
SITE, CARD, GUARDED, OPEN = "scgo"
#: Pages with shared open lines that may be broadcast; beyond it pages are shuffled once.
SHARED_ROWS = 50_000
#: Equal pairs of lines up to which chains are built; beyond it lines are aligned by bits.
MOST_PAIRS = 2_000_000


def _traits(name: str, attrs: str) -> set[str]:
    """What a start tag's names and roles say of it: site, card, story, body, main."""
    found: set[str] = set()
    if not attrs or not ("=" in attrs or "hidden" in attrs):
        return found
    for key, a, b, c in _ATTR.findall(attrs):
        key, value = key.lower(), (a or b or c).lower()
        if key == "role":
            found |= {"site"} if value in _BAD_ROLES else {"main"} if value == "main" else set()
        elif key == "hidden" or (key == "aria-hidden" and value == "true"):
            found |= {"site"}
        elif key in ("class", "id"):
            for word in value.replace("_", "-").split():
                parts = [p for p in word.split("-") if p]
                if word in _SITE_NAMES or any(p in _BAD_NAMES for p in parts) and all(p in _BAD_NAMES or p in _BOX_NAMES for p in parts):
                    found.add("site")
                if any(p in _CARD_NAMES for p in parts):
                    found.add("card")
                found |= {"story"} if word in _STORY_NAMES else {"body"} if word in _BODY_NAMES else set()
    return found


def _weigh(lines: list[tuple[str, dict[str, int]]]) -> str:
    """A letter for each line from the blocks it stands in (block numbers by role)."""
    length: dict[tuple[str, int], int] = defaultdict(int)
    for text, at in lines:
        if not (at["site"] or at["card"]):
            for role in ("article", "main", "story", "body"):
                length[role, at[role]] += len(text)

    def longest(role: str, among: set[int]) -> int:
        return max(among, key=lambda i: (length[role, i], -i))

    def numbers(role: str, within: str | None = None) -> set[int]:
        return {at[role] for _, at in lines if at[role] and not (at["site"] or at["card"]) and (within is None or at[within])}

    articles, mains, inside = numbers("article"), numbers("main"), numbers("article", "main")
    if mains and not inside:
        guarded, candidate = (lambda at: at["main"]), (lambda at: at["main"] or at["article"])
    elif articles:
        story = longest("article", inside or articles)
        guarded, candidate = (lambda at: at["article"] == story), (lambda at: at["main"] or at["article"])
    elif stories := numbers("story"):
        story = longest("story", stories)
        guarded, candidate = (lambda at: at["story"] == story), (lambda at: at["story"])
    elif numbers("body"):
        guarded, candidate = (lambda at: False), (lambda at: at["body"])
    else:
        guarded, candidate = (lambda at: False), (lambda at: True)
    return "".join(SITE if at["site"] else CARD if at["card"] else GUARDED if guarded(at) else OPEN if candidate(at) else SITE for _, at in lines)


def page_lines(page: str | None) -> tuple[list[str], str]:
    """(lines of the page, a letter for each that says how its structure weighs it)."""
    page = page or ""
    lines: list[tuple[str, dict[str, int]]] = []
    open_tags: list[tuple[str, tuple[str, ...]]] = []  # (tag, roles it opened)
    buffers: list[list[str]] = [[]]  # an inline part of the site has one of its own, the line around it goes on
    inside = dict.fromkeys(("site", "card", "article", "main", "story", "body"), 0)  # number of the outermost open block
    depth = dict.fromkeys(inside, 0)
    count = 0

    def flush() -> None:
        line = " ".join("".join(buffers[-1]).split())
        buffers[-1].clear()
        if line:
            lines.append((line, dict(inside)))

    def close(at: int) -> None:
        while len(open_tags) > at:
            name, roles = open_tags.pop()
            if roles and name in _INLINE:
                flush()
                buffers.pop()
            for role in roles:
                depth[role] -= 1
                if not depth[role]:
                    inside[role] = 0

    at, end = 0, len(page)
    while at < end:
        m = _TAG.search(page, at)
        stop = m.start() if m else end
        if stop > at:
            piece = page[at:stop]
            buffers[-1].append(html.unescape(piece) if "&" in piece else piece)
        if not m:
            break
        at = m.end() if m.end() > stop else stop + 1
        if m["cdata"]:
            buffers[-1].append(m["cdata"])
        name = (m["name"] or "").lower()
        if not name:
            continue
        if m["end"]:
            if name not in _INLINE:
                flush()
            places = [i for i, (t, _) in enumerate(open_tags) if t == name]
            if places:
                close(places[-1])
            continue
        if name in _RAW:
            if not m["attrs"].rstrip().endswith("/") or name in ("script", "style", "title", "textarea"):
                shut = re.compile(rf"</{name}\b[^>]*(?:>|\Z)", re.I).search(page, at)
                at = shut.end() if shut else end
            continue
        if name not in _INLINE:
            flush()
        if name in _VOID:
            continue
        traits = _traits(name, m["attrs"]) if name not in ("body", "html") else set()
        roles = [role for role, is_it in (
            ("site", name in _SKIP or "site" in traits or name == "header" and not (inside["article"] or inside["main"])),
            ("card", name == "article" and "card" in traits),
            ("article", name == "article" and "card" not in traits),
            ("main", name == "main" or "main" in traits),
            ("story", "story" in traits),
            ("body", "body" in traits),
        ) if is_it and (role == "site" or name not in _INLINE)]
        if roles or name not in _INLINE:  # inline tags without a role need no place in the stack
            if name == "p":  # an open paragraph ends here
                while open_tags and open_tags[-1] == ("p", ()):
                    open_tags.pop()
            if roles and name in _INLINE:
                buffers.append([])
            for role in roles:
                depth[role] += 1
                if depth[role] == 1:
                    count += 1
                    inside[role] = count
            open_tags.append((name, tuple(roles)))
    close(0)
    flush()
    return [x for x, _ in lines], _weigh(lines)


def common_lines(a: list, b: list) -> set[int]:
    """Places in ``a`` of one longest common subsequence with ``b``.

    Equal ends are set aside. The rest is solved over its equal pairs, or bit
    by bit where frequent lines make these many.
    """
    head = 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    found = set(range(head)) | set(range(len(a) - tail, len(a)))
    places = defaultdict(list)
    for j in range(head, len(b) - tail):
        places[b[j]].append(j)
    met = [i for i in range(head, len(a) - tail) if a[i] in places]
    if sum(len(places[a[i]]) for i in met) > MOST_PAIRS:
        known = {a[i] for i in met}
        return found | _by_bits([(i, a[i]) for i in met], [b[j] for j in range(head, len(b) - tail) if b[j] in known])
    ends: list[int] = []  # least end in b of a common subsequence of each length
    chain: list[tuple | None] = []
    for i in met:
        for j in reversed(places[a[i]]):
            k = bisect.bisect_left(ends, j)
            link = (i, chain[k - 1] if k else None)
            if k == len(ends):
                ends.append(j)
                chain.append(link)
            else:
                ends[k], chain[k] = j, link
    link = chain[-1] if chain else None
    while link:
        found.add(link[0])
        link = link[1]
    return found


def _lengths(a: list, b: list) -> np.ndarray:
    """Length of a longest common subsequence of ``a`` with each prefix of ``b``."""
    masks: dict = defaultdict(int)
    for j, x in enumerate(b):
        masks[x] |= 1 << j
    full = row = (1 << len(b)) - 1
    for x in a:
        u = row & masks.get(x, 0)
        row = ((row + u) | (row - u)) & full
    bits = np.unpackbits(np.frombuffer(row.to_bytes(-(-len(b) // 8) or 1, "little"), np.uint8), bitorder="little")[: len(b)]
    return np.concatenate(([0], np.cumsum(1 - bits.astype(np.int64))))


def _by_bits(a: list[tuple[int, object]], b: list) -> set[int]:
    """The same by halving ``a``: memory grows with the number of lines only."""
    if not a or not b:
        return set()
    if len(a) == 1:
        return {a[0][0]} if a[0][1] in b else set()
    half = len(a) // 2
    first, second = [x for _, x in a[:half]], [x for _, x in a[half:]]
    at = int((_lengths(first, b) + _lengths(second[::-1], b[::-1])[::-1]).argmax())
    return _by_bits(a[:half], b[:at]) | _by_bits(a[half:], b[at:])


def kept_text(lines: list[str], kinds: str, shared: set[int] | frozenset[int] = frozenset()) -> str:
    """The text of a page: guarded lines, and open ones that are not shared."""
    kept = [x for i, (x, k) in enumerate(zip(lines, kinds, strict=True)) if k == GUARDED or k == OPEN and i not in shared]
    return " ".join(kept or [x for x, k in zip(lines, kinds, strict=True) if k == OPEN] or [x for x, k in zip(lines, kinds, strict=True) if k == CARD])


def split_url(url: str | None) -> tuple[str, str]:
    """Host in lower case, and path without query and fragment."""
    m = re.match(r"(?:[a-zA-Z][a-zA-Z0-9+.-]*:)?//([^/?#]*)([^?#]*)", url or "")
    return (m[1].lower(), m[2]) if m else ("", re.split(r"[?#]", url or "", maxsplit=1)[0])


def _hash(line: str) -> int:
    return xxhash.xxh3_64_intdigest(line.encode("utf-8", "surrogatepass")) - (1 << 63)


def _outlined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Hashes and letters of each page's lines, and where its URL puts it."""
    for batch in batches:
        done = [page_lines(p) for p in batch.column(3).to_pylist()]
        split = [split_url(u) for u in batch.column(2).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([h for h, _ in split], pa.string()), pa.array([p for _, p in split], pa.string()), pa.array([k for _, k in done], pa.string()), pa.array([[_hash(x) for x in lines] for lines, _ in done], pa.list_(pa.int64()))], names=["_key", "_id", "_host", "_path", "_kinds", "_lines"])


def _aligned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each page: the open lines that it shares with its partner."""
    for batch in batches:
        own, kinds, other = (batch.column(i).to_pylist() for i in (2, 3, 4))
        gone = [[i for i in sorted(common_lines(a, b)) if k[i] == OPEN] for a, k, b in zip(own, kinds, other, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(gone, pa.list_(pa.int32()))], names=["_key", "_id", "_gone"])


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        pages, gone = batch.column(2).to_pylist(), batch.column(3).to_pylist()
        text = [kept_text(*page_lines(p), frozenset(g or ())) for p, g in zip(pages, gone, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(text, pa.string())], names=["_id", "_url", "_text"])


def nearest_pages(outlines: DataFrame) -> DataFrame:
    """(_key, _id, _pk, _pi): each page and the neighbour in its host that shares the longer path, the earlier one on ties."""
    placed = written(ordinal(outlines.select("_host", "_path", "_id", "_key"), ["_host", "_path", "_id", "_key"]), "order")
    beside = placed.select(F.col("ordinal").alias("o"), F.col("_host").alias("h"), F.col("_path").alias("p"), F.col("_key").alias("k"), F.col("_id").alias("i"))
    near = placed.select("*", F.explode(F.array(F.lit(-1), F.lit(1))).alias("step")).join(beside, F.col("ordinal") + F.col("step") == F.col("o")).where("_host = h")
    a, b = F.split("_path", "/"), F.split("p", "/")
    same = F.size(F.filter(F.sequence(F.lit(1), F.least(F.size(a), F.size(b))), lambda i: F.slice(a, 1, i) == F.slice(b, 1, i)))
    best = near.groupBy("_key", "_id").agg(F.max(F.struct(same.alias("n"), (-F.col("step")).alias("s"), "k", "i")).alias("m"))
    return best.select("_key", "_id", F.col("m.k").alias("_pk"), F.col("m.i").alias("_pi"))


def shared_lines(outlines: DataFrame) -> DataFrame:
    """(_key, _id, _gone): places of open lines that a page shares with its nearest page; pages with none are left out."""
    partner = nearest_pages(outlines)
    other = outlines.select(F.col("_key").alias("_pk"), F.col("_id").alias("_pi"), F.col("_lines").alias("_other"))
    pairs = outlines.select("_key", "_id", "_lines", "_kinds").join(partner, ["_key", "_id"]).join(other, ["_pk", "_pi"])
    found = pairs.select("_key", "_id", "_lines", "_kinds", "_other").mapInArrow(_aligned, "_key long, _id long, _gone array<int>")
    return found.where(F.size("_gone") > 0)


def extract_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per input row: id, url, text, n_chars (code points).

    Null html gives an empty text. Rows whose url is null form a host of
    their own. Rows that repeat id, url and html are one page for pairing and
    come back as often as they came. An empty table gives an empty result;
    extra columns are ignored.
    """
    page_id, url, page = F.col(id_col).cast("long"), F.col(url_col).cast("string"), F.col(html_col).cast("string")
    # pages are told apart by a 64-bit hash of the row beside their id; null ids count as -1 there
    base = pages.select(F.xxhash64(page_id, url, page).alias("_key"), F.coalesce(page_id, F.lit(-1).cast("long")).alias("_id"), url.alias("_url"), page.alias("_page"), page_id.alias("_shown"))
    outline = base.select("_key", "_id", "_url", "_page").mapInArrow(_outlined, "_key long, _id long, _host string, _path string, _kinds string, _lines array<long>")
    gone = checked_broadcast(written(shared_lines(written(outline.dropDuplicates(["_key", "_id"]), "outline")), "shared"), SHARED_ROWS)
    met = base.join(gone, ["_key", "_id"], "left").select("_shown", "_url", "_page", "_gone")
    out = met.mapInArrow(_texts, "_id long, _url string, _text string")
    return out.select(F.col("_id").alias(id_col), F.col("_url").alias(url_col), F.col("_text").alias("text"), F.length("_text").cast("long").alias("n_chars"))
