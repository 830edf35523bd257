"""HTML extraction by wrappers: union-free regular expressions inferred from the token streams of one host's pages.

A page is a stream of block tags and text slots; neighbouring equal stretches fold into repeated groups. A wrapper is such a stream whose
parts may be optional. A page is aligned with its host's wrapper by a longest common subsequence; single stretches that the other side repeats
are taken as repetitions, parts without a partner become optional, and a slot whose texts differ becomes a variable slot.
Wrappers of parts of a host's pages are aligned with each other the same way, so all pages take part, in two rounds of bounded groups.

What is extracted: usable blocks (not those of navigation, notices and so on) whose slots vary among the host's pages, optional ones among them. An article or main element is
evidence: if the page has such elements, blocks come from them, and one that is constant for the most part, though not all of it, is taken for near copies of one article and
stays whole. Without such an element they come from the container that holds most of the varying text. If no slot varies all usable blocks stay.

A text is constant if all pages that have its slot have the text, at least two of them say otherwise different things, and, for an optional slot, most of the host's pages have it.

Defined cases: null or empty html gives an empty text; a broken end leaves elements open to the end; a null or odd url is a host of its own
name; repeated pages are extracted alike; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import html as entities
import pickle
import re
from collections import Counter
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, materialise, table

#: Hosts whose unfinished wrappers a task holds at once, groups of a host's partial wrappers, bytes of wrappers that are broadcast.
TASK_HOSTS, SALTS, WRAPPER_BYTES = 500, 32, 48 << 20
#: Longest stretch tried as a repeated unit, cells (bits) of an alignment held at once.
UNIT, CELLS = 8, 1 << 28
VARIED, NONE = 0, frozenset()

# Fixed word lists: elements by their role.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q ruby rt rp s samp small span strike strong sub sup time tt u var wbr picture source".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe svg textarea select object math canvas".split())
DROPPED = frozenset("nav footer aside form head menu dialog button".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
SELF_CLOSING = {"li": frozenset({"li"}), "dt": frozenset({"dt", "dd"}), "dd": frozenset({"dt", "dd"}), "tr": frozenset({"tr", "td", "th"}), "td": frozenset({"td", "th"}), "th": frozenset({"td", "th"}), "option": frozenset({"option"})}
SCOPES = frozenset("ul ol dl table select article body div section main".split())
BAD_NAMES = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert sidebar widget nav navbar navigation menu breadcrumb breadcrumbs footer comment comments disqus reply replies respond share sharing social related recommended newsletter subscribe subscription popup modal overlay login signup search toolbar pagination pager".split())
BAD_ROLES = frozenset("navigation banner contentinfo complementary search form alert dialog menu".split())
MAIN = frozenset("article main".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*|[^>]*)>", re.S)
_CUT_TAG = re.compile(r"<(?:/?[a-zA-Z]|!)[^>]*\Z")
_ATTR = re.compile(r"""([a-zA-Z_:][-\w:.]*)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_NAME = re.compile(r"[a-z]+")


def _traits(tail: str) -> tuple[str, bool]:
    """(class names, whether the attributes speak against main text)."""
    if not tail or tail.isspace():
        return "", False
    found = {m[1].lower(): (m[2] or m[3] or m[4] or "") for m in _ATTR.finditer(tail)}
    names = _NAME.findall((found.get("class", "") + " " + found.get("id", "")).lower())
    bad = bool(BAD_NAMES.intersection(names)) or found.get("role", "").lower() in BAD_ROLES or "hidden" in found or found.get("aria-hidden") == "true"
    bad |= "display:none" in found.get("style", "").replace(" ", "").lower()
    return " ".join(sorted(found.get("class", "").split())), bad


class Page:
    """Blocks and block-tag stream of one page."""

    __slots__ = ("stream", "slots", "texts", "good", "main", "path")

    def __init__(self, html: str):
        self.stream: list[str] = []
        self.slots: list[int] = []  # block number of each stream token, -1 for tags
        self.texts: list[str] = []
        self.good: list[bool] = []  # not inside navigation and so on
        self.main: list[int] = []  # number of the article or main element around the block, -1 if none
        self.path: list[str] = []  # the block's container
        stack: list[tuple[str, bool, int, str]] = []  # element, good, main, path
        good, main, path, mains = True, -1, "", 0
        text: list[str] = []
        at, end = 0, len(html)
        token = _TOKEN.search

        def block() -> None:
            said = " ".join(entities.unescape("".join(text)).split())
            text.clear()
            if said:
                self.stream.append("#")
                self.slots.append(len(self.texts))
                self.texts.append(said)
                self.good.append(good)
                self.main.append(main)
                self.path.append(path)

        def tag(name: str) -> None:
            self.stream.append(name)
            self.slots.append(-1)

        while at < end:
            m = token(html, at)
            if m is None:
                text.append(_CUT_TAG.sub("", html[at:]))  # a tag that the page's end cuts off
                break
            if m.start() > at:
                text.append(html[at : m.start()])
            at = m.end()
            name = m[2]
            if name is None:
                continue
            name = name.lower()
            if name in RAW:
                if not m[1] and not m[3].rstrip().endswith("/"):
                    close = re.compile(rf"</{name}\b[^>]*>", re.I).search(html, at)
                    at = close.end() if close else end
                continue
            if name in INLINE:
                if name == "br":
                    text.append("\n")
                elif not m[1] and m[3] and name not in VOID and _traits(m[3])[1]:
                    # an inline element that speaks against main text is cut out with what it holds
                    close = re.compile(rf"</{name}\b[^>]*>", re.I).search(html, at)
                    at = close.end() if close else at
                continue
            block()
            if m[1]:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == name:
                        del stack[k:]
                        break
                else:
                    continue
                if name not in ("p", "li"):
                    tag("/" + name)
            else:
                if name in CLOSES_P:
                    for k in range(len(stack) - 1, -1, -1):
                        if stack[k][0] == "p":
                            del stack[k:]
                            break
                        if stack[k][0] in SCOPES:
                            break
                elif name in SELF_CLOSING:
                    for k in range(len(stack) - 1, -1, -1):
                        if stack[k][0] in SELF_CLOSING[name]:
                            del stack[k:]
                            break
                        if stack[k][0] in SCOPES:
                            break
                cls, bad = _traits(m[3])
                good, main, path = (stack[-1][1:]) if stack else (True, -1, "")
                if name in MAIN and main < 0 and good and not bad:
                    mains += 1
                    main = mains
                good = good and not bad and name not in DROPPED and not (name == "header" and main < 0)
                path = f"{path}/{name}"
                tag(f"{name}.{cls}" if cls else name)
                if name not in VOID:
                    stack.append((name, good, main, path))
            good, main, path = (stack[-1][1:]) if stack else (True, -1, "")
        block()


def fold(stream: list, slots: list[list[int]]) -> tuple[list, list[list[int]]]:
    """Neighbouring equal stretches as repeated groups ("rep", unit); slots lists the blocks under every item."""
    for size in range(1, UNIT + 1):
        out, own, i, n = [], [], 0, len(stream)
        while i < n:
            unit = stream[i : i + size]
            j = i + size
            if j + size <= n and stream[j] == unit[0] and stream[j : j + size] == unit and any(x == "#" or isinstance(x, tuple) for x in unit):
                while stream[j : j + size] == unit:
                    j += size
                out.append(("rep", tuple(unit)))
                own.append([b for s in slots[i:j] for b in s])
                i = j
            else:
                out.append(stream[i])
                own.append(slots[i])
                i += 1
        stream, slots = out, own
    return stream, slots


def absorb(stream: list, extra: list, units: list[tuple], join) -> tuple[list, list]:
    """Single stretches equal to a unit that the other side repeats become that repeated group; a group next to itself is one group."""
    for unit in units:
        k, target, out, own, i = len(unit), ("rep", unit), [], [], 0
        unit = list(unit)
        while i < len(stream):
            if stream[i] == target or stream[i : i + k] == unit:
                n = 1 if stream[i] == target else k
                part = extra[i : i + n]
                if out and out[-1] == target:
                    own[-1] = join([own[-1], *part])
                else:
                    out.append(target)
                    own.append(join(part))
                i += n
            else:
                out.append(stream[i])
                own.append(extra[i])
                i += 1
        stream, extra = out, own
    return stream, extra


def _units(stream: list) -> list[tuple]:
    return sorted({x[1] for x in stream if isinstance(x, tuple)}, key=lambda u: (len(u), repr(u)))


def _suffixes(x: list, y: list, keep: bool = True) -> list[int]:
    """For every suffix of x (or only all of x) a bit set: its bit k is 0 where y's suffix of k + 1 items has a longer common subsequence with it than that of k."""
    at: dict = {}
    for k, t in enumerate(reversed(y)):
        at[t] = at.get(t, 0) | 1 << k
    full = v = (1 << len(y)) - 1
    rows = [v]
    for t in reversed(x):
        u = v & at.get(t, 0)
        v = ((v + u) | (v - u)) & full
        if keep:
            rows.append(v)
    return rows[::-1] if keep else [v]


def _lengths(x: list, y: list) -> list[int]:
    """Length of the longest common subsequence of x and each suffix of y, the empty one first."""
    v, m = _suffixes(x, y, False)[0], len(y)
    return [0, *accumulate(1 - int(c) for c in reversed(f"{v:0{m}b}"))] if m else [0]


def _lcs(x: list, y: list) -> list[tuple[int, int]]:
    """Longest common subsequence as in align, exact at any length; beyond CELLS it halves x, so that memory stays linear."""
    n, m = len(x), len(y)
    if n > 1 and n * m > CELLS:
        half = n // 2
        ahead, behind = _lengths(x[:half][::-1], y[::-1]), _lengths(x[half:], y)
        cut = max(range(m + 1), key=lambda q: ahead[q] + behind[m - q])
        return _lcs(x[:half], y[:cut]) + [(p + half if p >= 0 else -1, q + cut if q >= 0 else -1) for p, q in _lcs(x[half:], y[cut:])]
    rows, out, p, q = _suffixes(x, y), [], 0, 0
    while p < n and q < m:
        low = (1 << (m - q)) - 1
        if x[p] == y[q]:
            out.append((p, q))
            p, q = p + 1, q + 1
        elif not rows[p] >> (m - q - 1) & 1 or (rows[p] & low).bit_count() == (rows[p + 1] & low).bit_count():
            out.append((p, -1))
            p += 1
        else:
            out.append((-1, q))
            q += 1
    return out + [(k, -1) for k in range(p, n)] + [(-1, k) for k in range(q, m)]


def align(a: list, b: list) -> list[tuple[int, int]]:
    """Longest common subsequence of two streams as (place in a or -1, place in b or -1), ends matched first."""
    lo = 0
    while lo < len(a) and lo < len(b) and a[lo] == b[lo]:
        lo += 1
    i, j = len(a), len(b)
    while i > lo and j > lo and a[i - 1] == b[j - 1]:
        i, j = i - 1, j - 1
    head, tail = [(k, k) for k in range(lo)], [(i + k, j + k) for k in range(len(a) - i)]
    x, y = a[lo:i], b[lo:j]
    mid = [(lo + p if p >= 0 else -1, lo + q if q >= 0 else -1) for p, q in _lcs(x, y)]
    return [*head, *mid, *tail]


class Wrapper:
    """items: parts of the expression; facts: (optional, value, pages, common, least, most).

    value: the common text's hash or VARIED; common: hashes of the blocks that all these pages have there; least and most of these pages' marks differ
    if the pages do.
    """

    __slots__ = ("items", "facts", "pages")

    def __init__(self, items: list, facts: list[tuple], pages: int):
        self.items, self.facts, self.pages = items, facts, pages

    @classmethod
    def of(cls, page: Page) -> Wrapper:
        items, blocks = fold(page.stream, [[s] if s >= 0 else [] for s in page.slots])
        mark = _mark(page)
        return cls(items, [(False, _value(page, b), 1, frozenset(_hash(page.texts[k]) for k in b) if b else NONE, mark, mark) for b in blocks], 1)

    def merge(self, other: Wrapper) -> Wrapper:
        units = sorted({*_units(self.items), *_units(other.items)}, key=lambda u: (len(u), repr(u)))
        a, fa = absorb(self.items, self.facts, units, _join)
        b, fb = absorb(other.items, other.facts, units, _join)
        items, facts = [], []
        for i, j in align(a, b):
            if i >= 0 and j >= 0:
                x, y = fa[i], fb[j]
                items.append(a[i])
                facts.append((x[0] or y[0], x[1] if x[1] == y[1] else VARIED, x[2] + y[2], x[3] & y[3] or NONE, min(x[4], y[4]), max(x[5], y[5])))
            else:
                item, fact = (a[i], fa[i]) if i >= 0 else (b[j], fb[j])
                items.append(item)
                facts.append((True, *fact[1:]))
        return Wrapper(items, facts, self.pages + other.pages)

    def constant(self, k: int) -> frozenset:
        """Hashes of the blocks under item k that are template text."""
        optional, _, pages, common, least, most = self.facts[k]
        return common if common and least != most and (not optional or 2 * pages > self.pages) else NONE

    def trim(self) -> Wrapper:
        """Without the texts of single pages, once all pages are in."""
        return Wrapper(self.items, [(*f[:3], f[3] if f[4] != f[5] else NONE, *f[4:]) for f in self.facts], self.pages)

    def expression(self) -> str:
        """The wrapper as text: groups in brackets, ? for optional, + for repeated, # and = for variable and constant slots."""

        def show(x, fixed: bool) -> str:
            return "(" + " ".join(show(y, fixed) for y in x[1]) + ")+" if isinstance(x, tuple) else ("=" if fixed else "#") if x == "#" else f"<{x}>"

        return " ".join(f"({show(x, f[1] != VARIED and f[4] != f[5])})?" if f[0] else show(x, f[1] != VARIED and f[4] != f[5]) for x, f in zip(self.items, self.facts, strict=True))

    def to_bytes(self) -> bytes:
        return pickle.dumps((self.items, self.facts, self.pages), protocol=4)

    @classmethod
    def from_bytes(cls, data: bytes) -> Wrapper:
        return cls(*pickle.loads(data))


def _hash(text: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text.encode("utf-8", "replace")) | 1


def _value(page: Page, blocks: list[int]) -> int:
    return _hash("\n".join(page.texts[b] for b in blocks)) if blocks else 1


def _mark(page: Page) -> int:
    """Of what the page says: its usable text, inside article or main if it has them. Copies in other frames have the same mark."""
    usable = [b for b, g in enumerate(page.good) if g]
    return _value(page, [b for b in usable if page.main[b] >= 0] or usable)


def _join(facts: list[tuple]) -> tuple:
    """Facts of parts that become one group; what optional parts have in common is not common to the group's pages."""
    if len(facts) == 1:
        return facts[0]
    sure = [f for f in facts if not f[0]]
    common = frozenset().union(*(f[3] for f in sure)) or NONE
    return not sure, VARIED, max(f[2] for f in facts), common, min(f[4] for f in sure or facts), max(f[5] for f in sure or facts)


HOST = re.compile(r"^[a-zA-Z][\w+.-]*://(?:[^/@?#]*@)?([^/:?#]*)")


def host_of(url: str | None) -> str:
    m = HOST.match(url or "")
    return m[1].lower() if m and m[1] else (url or "")


def _partial(batches):
    from pyspark import TaskContext

    salt, held = TaskContext.get().partitionId() % SALTS, {}

    def rows():
        out = pa.record_batch([pa.array(list(held), pa.string()), pa.array([salt] * len(held), pa.int32()), pa.array([w.to_bytes() for w in held.values()], pa.binary())], ["host", "salt", "wrapper"])
        held.clear()
        return out

    for b in batches:
        for url, html in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            host, w = host_of(url), Wrapper.of(Page(html or ""))
            held[host] = held[host].merge(w) if host in held else w
        if len(held) >= TASK_HOSTS:
            yield rows()
    if held:
        yield rows()


def _merged(t: pa.Table) -> pa.Table:
    parts = sorted(t["wrapper"].to_pylist())
    w = Wrapper.from_bytes(parts[0])
    for p in parts[1:]:
        w = w.merge(Wrapper.from_bytes(p))
    cols = {c: t[c][:1] for c in t.column_names if c != "wrapper"}
    return pa.table(cols | {"wrapper": pa.array([w.to_bytes()], pa.binary())})


def _whole(t: pa.Table) -> pa.Table:
    w = Wrapper.from_bytes(_merged(t)["wrapper"][0].as_py()).trim()
    return pa.table({"host": t["host"][:1], "wrapper": pa.array([w.to_bytes()], pa.binary())})


def infer(pages: DataFrame) -> DataFrame:
    """(host, wrapper) from all pages (url, html): within tasks, then within salted groups, then for each host."""
    bound_batches(pages.sparkSession)
    part = pages.select(F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(_partial, "host string, salt int, wrapper binary")
    salted = part.groupBy("host", "salt").applyInArrow(_merged, "host string, salt int, wrapper binary")
    return materialise(salted.select("host", "wrapper").groupBy("host").applyInArrow(_whole, "host string, wrapper binary"))


def extract(page: Page, wrapper: Wrapper | None, plans: dict | None = None) -> str:
    """The page's main text, its blocks in order."""
    usable = [b for b, g in enumerate(page.good) if g]
    inside = [b for b in usable if page.main[b] >= 0]
    fixed = _fixed_blocks(page, wrapper, plans) if wrapper is not None and wrapper.pages > 1 else set()
    if inside:
        # of several such elements, those that say something of their own
        own, same = Counter(), Counter()
        for b in inside:
            (same if b in fixed else own)[page.main[b]] += len(page.texts[b])
        kept = own or same
        return "\n\n".join(page.texts[b] for b in inside if page.main[b] in kept and (b not in fixed or same[page.main[b]] > own[page.main[b]]))
    varied = [b for b in usable if b not in fixed] or usable
    if not varied:
        return ""
    size: Counter = Counter()
    for b in varied:
        size[page.path[b].rpartition("/")[0]] += len(page.texts[b])
    home = max(size, key=lambda k: (size[k], -len(k)))
    return "\n\n".join(page.texts[b] for b in varied if (page.path[b] + "/").startswith(home + "/"))


def _fixed_blocks(page: Page, w: Wrapper, plans: dict | None) -> set[int]:
    """Blocks that lie in constant slots of the wrapper."""
    items, blocks = fold(page.stream, [[s] if s >= 0 else [] for s in page.slots])
    key = tuple(items)
    if plans is not None and key in plans:
        pairs, items, merged = plans[key]
    else:
        units = _units(w.items)
        items, merged = absorb(items, [[k] for k in range(len(items))], units, lambda parts: [k for p in parts for k in p])
        pairs = align(w.items, items)
        if plans is not None:
            plans[key] = pairs, items, merged
    out: set[int] = set()
    for i, j in pairs:
        if i >= 0 and j >= 0 and (common := w.constant(i)):
            out.update(b for k in merged[j] for b in blocks[k] if _hash(page.texts[b]) in common)
    return out


def extract_pages(pages: DataFrame, wrappers: DataFrame | None = None, limit: int = WRAPPER_BYTES) -> DataFrame:
    """(page_id, url, text, n_chars) of all pages, by their hosts' wrappers."""
    spark = pages.sparkSession
    wrappers = infer(pages) if wrappers is None else wrappers
    own = pages.select("page_id", F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    total = wrappers.agg(F.sum(F.length("wrapper") + F.length("host"))).first()[0] or 0
    bound_batches(spark)
    held = None
    if total <= limit:
        held = spark.sparkContext.broadcast({r.host: bytes(r.wrapper) for r in wrappers.toLocalIterator()})
        joined = own.withColumn("wrapper", F.lit(None).cast("binary"))
    else:
        joined = own.withColumn("dm_host", _host_column()).join(wrappers.withColumnRenamed("host", "dm_host"), "dm_host", "left").select("page_id", "url", "html", "wrapper")
    schema = own.select("page_id", "url", F.lit("").alias("text"), F.lit(0).cast("long").alias("n_chars")).schema
    for f in schema:
        f.nullable = True

    def run(batches):
        known: dict[str, tuple[Wrapper | None, dict]] = {}
        for b in batches:
            texts = []
            for url, html, data in zip(*(b.column(k).to_pylist() for k in (1, 2, 3)), strict=True):
                host = host_of(url)
                if host not in known:
                    if len(known) > TASK_HOSTS:
                        known.clear()
                    data = held.value.get(host) if held is not None else data
                    known[host] = (Wrapper.from_bytes(data) if data else None, {})
                w, plans = known[host]
                if len(plans) > 1000:
                    plans.clear()
                texts.append(extract(Page(html or ""), w, plans))
            yield pa.record_batch([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema.names)

    return joined.mapInArrow(run, schema)


def _host_column():
    found = F.lower(F.regexp_extract("url", r"^[a-zA-Z][\w+.-]*://(?:[^/@?#]*@)?([^/:?#]*)", 1))
    return F.when(found != "", found).otherwise(F.coalesce("url", F.lit("")))


def op9_html_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))


def page_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(host, pages, expression): the inferred wrappers as text."""
    bound_batches(spark)

    def run(batches):
        for b in batches:
            w = [Wrapper.from_bytes(x) for x in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array([x.pages for x in w], pa.int64()), pa.array([x.expression() for x in w], pa.string())], ["host", "pages", "expression"])

    return infer(table(spark, sf_dir, "pages")).mapInArrow(run, "host string, pages long, expression string")
