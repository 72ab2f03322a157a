"""Main text of web pages by union-free wrappers of their hosts.

A wrapper is what all distinct pages of a host have in common.  Each text block
has a place, the path of open elements with their classes and ids.  A text that
at least half of a host's distinct pages (three at least) have at one place is
the host's furniture, constant or optional; places whose texts differ are slots.
The content root is the deepest container that holds most slot text outside
furniture elements.  Hosts of fewer than three distinct pages have no wrapper:
their pages are cut by article (or main) elements, else at the body.

Scale: places are counted by (host, place and text) with partial sums, over all
pages and whole pages; copies of a page count once.  A host's wrapper, its root
and at most twice its mean number of blocks in furniture, then meets the host's
pages by an equal join on the host and a share of its pages, so that a host with
a third of all pages spreads; results don't depend on partitions.  `infer` also writes a few pages' wrapper as a regular
expression, by aligning them in turn: differing texts become slots, runs of one
side optional groups, runs that follow each other repeated groups.

Defined cases: null or empty html gives an empty text; null urls form one host
without a name; pages of any length are read whole, broken markup is repaired as
browsers do in the cases met most (unclosed paragraphs, stray end tags); repeated
rows keep their rows; no page is dropped.
"""

from __future__ import annotations

import html
import itertools
import json
import re
from dataclasses import dataclass, field
from difflib import SequenceMatcher

import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from .common import checkpointed

LEAST_PAGES = 3
FURNITURE_SHARE = 0.5
ROOT_SHARE = 0.8
SHARES = 16
ROOTS = ("html", "body", "div", "section", "article", "main", "td", "table", "tbody", "tr", "center")

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|iframe|svg|textarea|select|object)\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*(?:/>|>.*?(?:</\1\s*>|\Z))"
    r"|</?[a-zA-Z](?:[^>\"']|\"[^\"]*\"|'[^']*')*>|<[!?/][^>]*>",
    re.S | re.I,
)
NAME = re.compile(r"<(/?)\s*([a-zA-Z][a-zA-Z0-9:-]*)")
ATTR = re.compile(r"\b(class|id|role|itemprop|hidden|style|aria-hidden)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
# Element names.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = set("address article aside blockquote body br caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
FURNITURE = set("nav header footer aside form button menu dialog head title label fieldset".split())
CLOSES = {"p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"}, "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"}}
ENDS_P = BLOCK - {"br", "p", "body", "html", "head"}
FURNITURE_WORD = re.compile(
    r"^(ads?|advert(isement|s|ising)?|banner|breadcrumbs?|comments?|comment-?(list|section|form|area)|cookies?|cookie-?(notice|banner|consent)|disqus|footer|header|masthead|menu|modal|nav(bar|igation)?|newsletter|notices?|notification|pager|pagination|popup|promo(tion)?|related|related-?posts|reader-?comments|replies|respond|share|sharing|sidebar|sidebar-?(left|right)|site-?(header|footer|nav|menu)|skip-?link|social|sponsor(ed)?|subscribe|subscription|tags|toolbar|widget|alert|gdpr|consent|discussion)$",
    re.I,
)
FURNITURE_ROLE = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "menu", "menubar"}


@dataclass
class Tag:
    name: str
    close: bool
    key: str  # name with class and id, as alignment sees it
    furniture: bool
    main: int  # 0 no, 1 main, 2 article


def _tag(raw: str) -> Tag | None:
    m = NAME.match(raw)
    if not m:
        return None
    name, close = m[2].lower(), bool(m[1])
    if close:
        return Tag(name, True, "/" + name, False, 0)
    key, furniture, main = name, name in FURNITURE, {"article": 2, "main": 1}.get(name, 0)
    if len(raw) > len(m[0]) + 1:
        for a in ATTR.finditer(raw, m.end()):
            attr, value = a[1].lower(), (a[2] or a[3] or a[4] or "").strip()
            if attr in ("class", "id"):
                key += f" {attr}={value}"
                if any(FURNITURE_WORD.match(w) for w in value.split()):
                    furniture = name not in ("body", "html")
                if re.search(r"(?i)(^|\s)(article|post|entry)[-_]?(body|content|text)(\s|$)", value):
                    main = max(main, 1)
            elif attr == "role":
                furniture = furniture or value.lower() in FURNITURE_ROLE
                main = {"main": max(main, 1), "article": 2}.get(value.lower(), main)
            elif attr == "itemprop" and value.lower() == "articlebody":
                main = max(main, 1)
            elif attr == "hidden" or attr == "aria-hidden" and value.lower() == "true" or attr == "style" and re.search(r"display\s*:\s*none", value, re.I):
                furniture = True
    return Tag(name, False, key, furniture, main)


def tokens(page: str | None) -> list[Tag | str]:
    """Tags and raw texts; comments, scripts, styles and declarations are left out."""
    page = page or ""
    out: list[Tag | str] = []
    at = 0
    for m in TOKEN.finditer(page):
        if m.start() > at:
            out.append(page[at : m.start()])
        at = m.end()
        if m[1] is None and page[m.start() + 1] not in "!?":
            t = _tag(m[0])
            if t:
                out.append(t)
    if at < len(page):
        out.append(page[at:])
    return out


# --- wrapper inference ---------------------------------------------------------


@dataclass
class Item:
    """One place of a wrapper: kind is tag, text, slot, opt or rep."""

    kind: str
    value: str = ""
    inner: list["Item"] = field(default_factory=list)
    path: str = ""
    weight: int = 0

    def key(self) -> str:
        if self.kind == "tag":
            return self.value
        if self.kind in ("text", "slot"):
            return "#"
        return ("+" if self.kind == "rep" else "?") + "(" + " ".join(i.key() for i in self.inner) + ")"


def items(stream: list[Tag | str]) -> list[Item]:
    """A page as wrapper places, each with the path of open elements; neighbouring equal runs are folded."""
    out, stack = [], []
    for t in stream:
        if isinstance(t, str):
            s = " ".join(html.unescape(t).split())
            if s:
                out.append(Item("text", s, path="/".join(stack), weight=len(s)))
        elif t.close:
            if t.name in stack:
                while stack.pop() != t.name:
                    pass
            out.append(Item("tag", t.key, path="/".join(stack)))
        else:
            if t.name in CLOSES and stack and stack[-1].split()[0] in CLOSES[t.name]:
                stack.pop()
            out.append(Item("tag", t.key, path="/".join(stack)))
            if t.name not in VOID:
                stack.append(t.name)
    return fold(out)


def fold(seq: list[Item], longest: int = 40) -> list[Item]:
    """Repeated groups: a run of places followed by the same run (texts aside) is one group."""
    keys = [i.key() for i in seq]
    out: list[Item] = []
    i = 0
    while i < len(seq):
        done = False
        if seq[i].kind == "tag" and not keys[i].startswith("/"):
            close = "/" + keys[i].split()[0]
            n = next((j - i + 1 for j in range(i + 1, min(len(seq), i + longest)) if keys[j] == close), 0)
            if n and keys[i : i + n] == keys[i + n : i + 2 * n]:
                group, k = seq[i : i + n], i + n
                while keys[k : k + n] == keys[i : i + n]:
                    group = [_meet(a, b) for a, b in zip(group, seq[k : k + n])]
                    k += n
                out.append(Item("rep", inner=group, path=seq[i].path))
                i, done = k, True
        if not done:
            out.append(seq[i])
            i += 1
    return out


def _meet(a: Item, b: Item) -> Item:
    if a.kind in ("text", "slot") and (a.kind != b.kind or a.value != b.value):
        return Item("slot", path=a.path, weight=max(a.weight, b.weight))
    if a.kind in ("opt", "rep"):
        return Item(a.kind, inner=[_meet(x, y) for x, y in zip(a.inner, b.inner)] if len(a.inner) == len(b.inner) else a.inner, path=a.path)
    return a


def align(wrapper: list[Item], page: list[Item]) -> list[Item]:
    """The wrapper generalised to accept the page too."""
    a, b = [i.key() for i in wrapper], [i.key() for i in page]
    out: list[Item] = []
    for op, i1, i2, j1, j2 in SequenceMatcher(None, a, b, autojunk=False).get_opcodes():
        if op == "equal":
            out += [_meet(x, y) for x, y in zip(wrapper[i1:i2], page[j1:j2])]
            continue
        for part in (wrapper[i1:i2], page[j1:j2]):
            if len(part) == 1 and part[0].kind in ("opt",):
                out.append(part[0])
            elif part and out and out[-1].kind == "rep" and [i.key() for i in part] == [i.key() for i in out[-1].inner]:
                out[-1] = Item("rep", inner=[_meet(x, y) for x, y in zip(out[-1].inner, part)], path=out[-1].path)
            elif part and not (out and out[-1].kind == "opt" and [i.key() for i in out[-1].inner] == [i.key() for i in part]):
                out.append(Item("opt", inner=part, path=part[0].path))
    return out


@dataclass
class Wrapper:
    places: list[Item]
    root: str  # place of the content root, "" for the body
    constants: set[int]  # keys of the furniture: place and text

    def expression(self) -> str:
        """The wrapper as a regular expression over tags and texts, without unions."""

        def show(seq):
            return " ".join({"tag": f"<{i.value}>", "text": json.dumps(i.value, ensure_ascii=False), "slot": "#TEXT"}.get(i.kind) or f"({show(i.inner)}){'+' if i.kind == 'rep' else '?'}" for i in seq)

        return show(self.places)


def infer(pages: list[str | None]) -> Wrapper:
    """Wrapper of a few pages of one host; `wrappers` finds the same root and furniture for tables."""
    streams = [x for x in map(items, map(tokens, pages)) if x]
    places = streams[0] if streams else []
    for x in streams[1:]:
        places = align(places, x)
    distinct = {signature(found): found for found in map(blocks, pages)}
    count: dict[int, int] = {}
    mass: dict[str, int] = {}
    for found in distinct.values():
        for k in {b.key for b in found}:
            count[k] = count.get(k, 0) + 1
    least = max(LEAST_PAGES, FURNITURE_SHARE * len(distinct))
    constants = {k for k, c in count.items() if c >= least}
    for b in itertools.chain(*distinct.values()):
        steps = b.place.split("/")
        for k in range(1, len(steps) + 1) if b.key not in constants else ():
            at = "/".join(steps[:k])
            mass[at] = mass.get(at, 0) + len(b.text)
    whole = max(mass.values(), default=0) if len(distinct) >= LEAST_PAGES else 0
    roots = [p for p, w in mass.items() if whole and w >= ROOT_SHARE * whole and re.split("[#/]", p.rsplit("/", 1)[-1])[0] in ROOTS]
    return Wrapper(places, max(roots, key=lambda p: (p.count("/"), p), default=""), constants)


# --- extraction -----------------------------------------------------------------


@dataclass
class Block:
    """A text block outside furniture elements, with its place and the ranks of the content elements it stands in, by their number."""

    place: str
    text: str
    regions: dict[int, int]

    @property
    def key(self) -> int:
        return (xxhash.xxh64_intdigest(self.place + "\0" + self.text) ^ 1 << 63) - (1 << 63)


def signature(found: list[Block]) -> int:
    """Equal for pages with the same blocks."""
    return (xxhash.xxh64_intdigest("\n".join(b.place + "\0" + b.text for b in found)) ^ 1 << 63) - (1 << 63)


def _step(t: Tag) -> str:
    """An element in a place: its name, and a hash of class and id without their numbers."""
    return t.name if t.key == t.name else f"{t.name}#{xxhash.xxh32_hexdigest(re.sub('[0-9]+', '0', t.key))}"


def blocks(page: str | None) -> list[Block]:
    """Text blocks in page order; what furniture elements hold is left out."""
    stream = tokens(page)
    out: list[Block] = []
    regions: list[tuple[int, int, int]] = []  # open content regions: depth, number, rank
    numbers = itertools.count()
    stack: list[tuple[str, bool, str]] = []  # name, furniture, step of a place
    hidden = 0
    piece: list[str] = []

    def flush():
        if piece:
            s = " ".join(html.unescape("".join(piece)).split())
            piece.clear()
            if s and not hidden:
                out.append(Block("/".join(step for _, _, step in stack), s, {k: r for _, k, r in regions}))

    def pop():
        nonlocal hidden
        hidden -= stack.pop()[1]
        while regions and len(stack) < regions[-1][0]:
            regions.pop()

    for t in stream:
        if isinstance(t, str):
            if not hidden:
                piece.append(t)
            continue
        if t.name in BLOCK:
            flush()
        if t.close:
            names = [n for n, _, _ in stack]
            if t.name in names:
                if t.name not in BLOCK and any(n in BLOCK for n in names[len(names) - names[::-1].index(t.name) :]):
                    continue  # a misnested inline end tag closes nothing
                flush() if t.name in BLOCK else None
                while stack[-1][0] != t.name:
                    pop()
                pop()
            continue
        if t.main == 2 and hidden and not any(r == 3 for _, _, r in regions):
            while hidden:  # an article inside furniture: the furniture was left open
                pop()
        if t.name in ENDS_P and stack:
            while stack and stack[-1][0] not in ENDS_P and "p" in [n for n, _, _ in stack]:
                if stack[-1][0] == "p":
                    pop()
                    break
                if "p" not in [n for n, _, _ in stack[max((k for k, (n, _, _) in enumerate(stack) if n in ENDS_P), default=-1) + 1 :]]:
                    break
                pop()
        elif t.name in CLOSES and stack:
            names = [n for n, _, _ in stack]
            limit = max((k for k, n in enumerate(names) if n in ENDS_P and n not in CLOSES), default=-1)
            k = max((k for k, n in enumerate(names) if n in CLOSES[t.name] and k > limit), default=-1)
            if k >= 0:
                while len(stack) > k:
                    pop()
        if t.name in VOID:
            continue
        inside = any(r == 3 for _, _, r in regions)
        furniture = t.furniture and not (t.main and not t.name in FURNITURE) and not (inside and t.name == "header")
        if t.main == 2:
            furniture = False
        stack.append((t.name, furniture, _step(t)))
        hidden += furniture
        if not hidden and t.main and not (inside and t.main == 2):
            regions.append((len(stack), next(numbers), 1 + t.main))
    flush()
    return out


def extract(page: str | None, wrapper: Wrapper | None = None) -> str:
    """Main text: blocks in page order, one line each."""
    return main_text(blocks(page), wrapper.root if wrapper else "", wrapper.constants if wrapper else set())


def main_text(found: list[Block], root: str, constants: set[int]) -> str:
    """The wrapper decides: slots of its root without furniture, wherever it stands.  Content elements of the top rank narrow that where they hold most of it."""
    kept = [b for b in found if b.key not in constants] or found  # a page of nothing else is no furniture
    scope = [b for b in kept if root and (b.place + "/").startswith(root + "/")] or kept
    top = max((r for b in scope for r in b.regions.values()), default=0)
    if top:
        tagged = [b for b in scope if top in b.regions.values()]
        if not root or 2 * sum(len(b.text) for b in tagged) >= sum(len(b.text) for b in scope):
            scope = tagged
    return "\n".join(b.text for b in scope)

def wrappers(seen: DataFrame) -> DataFrame:
    """host, root, constants of every host of at least three distinct pages; from (host, sig, blocks) rows of pages."""
    pages = checkpointed(seen.groupBy("host", "sig").agg(F.first("blocks").alias("blocks")))  # parsed once for what follows
    sizes = pages.groupBy("host").agg(F.count("*").alias("n")).filter(F.col("n") >= LEAST_PAGES)
    each = pages.select("host", F.explode("blocks").alias("b")).select("host", "b.*")
    common = each.groupBy("host", "key").agg(F.count("*").alias("c"), F.first("place").alias("place"), F.sum("size").alias("size")).filter(F.col("c") >= LEAST_PAGES)
    constant = common.join(sizes, "host").filter(F.col("c") >= FURNITURE_SHARE * F.col("n")).select("host", "key", "place", "size")
    # What varies at a place: all its text less its furniture.
    mass = each.select("host", "place", "size").unionByName(constant.select("host", "place", (-F.col("size")).alias("size"))).groupBy("host", "place").agg(F.sum("size").alias("size"))
    steps = F.split("place", "/")
    above = mass.select("host", "size", F.explode(F.transform(F.sequence(F.lit(1), F.size(steps)), lambda k: F.array_join(F.slice(steps, F.lit(1), k), "/"))).alias("place"))
    held = above.groupBy("host", "place").agg(F.sum("size").alias("size"))
    whole = held.groupBy("host").agg(F.max("size").alias("whole"))
    roots = held.join(whole, "host").filter((F.col("size") > 0) & (F.col("size") >= ROOT_SHARE * F.col("whole")) & F.regexp_extract("place", "([^/#]*)(#[^/]*)?$", 1).isin(*ROOTS))
    root = roots.groupBy("host").agg(F.max(F.struct(F.size(F.split("place", "/")).alias("k"), "place")).alias("r")).select("host", F.col("r.place").alias("root"))
    keys = constant.groupBy("host").agg(F.collect_list("key").alias("constants"))
    return sizes.select("host").join(root, "host", "left").join(keys, "host", "left")


def slices(batches, column: int, rows: int = 512, size: int = 4 << 20):
    """The batches in parts of at most so many rows, and bytes of a text column unless a row alone has more: what a page's blocks take in Python is many times its html."""
    for b in batches:
        sizes = pc.fill_null(pc.binary_length(b.column(column)), 0).to_numpy(zero_copy_only=False)
        at, held = 0, 0
        for k, n in enumerate(sizes.tolist()):
            if k > at and (k - at == rows or held + n > size):
                yield b.slice(at, k - at)
                at, held = k, 0
            held += n
        if at < b.num_rows:
            yield b.slice(at)


def run_host(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    from .url_filters import host

    named = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), F.coalesce(host(F.col(url_col)), F.lit("")).alias("host"))

    def see(batches):
        kind = pa.list_(pa.struct([("key", pa.int64()), ("place", pa.string()), ("size", pa.int64())]))
        for b in slices(batches, 1):
            sigs, rows = [], []
            for p in b.column(1).to_pylist():
                found = blocks(p)
                one: dict[int, dict] = {}
                for x in found:
                    one.setdefault(x.key, {"key": x.key, "place": x.place, "size": 0})["size"] += len(x.text)
                sigs.append(signature(found))
                rows.append(list(one.values()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sigs, pa.int64()), pa.array(rows, kind)], names=["host", "sig", "blocks"])

    seen = named.select("host", "html").mapInArrow(see, "host string, sig long, blocks array<struct<key: long, place: string, size: long>>")
    # A host's furniture is short beside its pages; they meet by an equal join on the host and one of 16 shares of its pages.
    found = wrappers(seen).withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(SHARES - 1))))
    met = named.withColumn("share", F.pmod(F.xxhash64("page_id", "url"), F.lit(SHARES)).cast("int")).join(checkpointed(found), ["host", "share"], "left")
    schema = T.StructType([T.StructField("page_id", pages.schema[id_col].dataType), T.StructField("url", T.StringType()), T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def work(batches):
        now, constants = None, set()
        for b in slices(batches, 2):
            texts = []
            for k, (p, h, root) in enumerate(zip(*(b.column(c).to_pylist() for c in (2, 3, 4)))):
                if h != now:
                    now, constants = h, set(b.column(5)[k].as_py() or ())
                texts.append(main_text(blocks(p), root or "", constants))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=schema.names)

    return met.select("page_id", "url", "html", "host", "root", "constants").mapInArrow(work, schema)
