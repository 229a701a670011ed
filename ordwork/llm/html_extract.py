"""Main text of web pages by wrappers: union-free regular expressions inferred from all pages of one host.

A page is a stream of tokens: tags and texts, each with the path of the elements around it. Inside a page, neighbouring sequences of
one shape fold into a repeated group. Pages of a host that fold alike are one class, whose texts are compared place by place; classes are
aligned one after the other. What only one side has becomes optional, and texts that differ become slots, while texts that stay the
same on all pages that have their place remain template. Where alignment would have a token more often than either side has it, as sides order
their parts differently, two that are near and all between become a free group: any number of its tokens in any order. So a wrapper has
no token more often than some page of the host, however many pages there are. It has tokens, template texts, slots, optional, repeated and free groups but no alternatives.
A text is main text if it stands in a slot, in no menu, header, footer, sidebar, notice, advert, form, script, style or comment, and
inside the article (or main part) if the wrapper has one. A text is template where at least TEMPLATE_PAGES different pages had it in one place,
and TEMPLATE_PAGES of every TEMPLATE_OF pages of the host; on a page of which template would take most and more than TEMPLATE_WORDS words, or all,
the host's pages were copies, and everything counts as slots. Every page is matched with its host's wrapper; one that doesn't match is aligned with it as in
inference, which generalises the wrapper for it.

Paths are chained digests with a few flags, so deep nesting costs no more than flat pages.

Each task merges the pages of a class that it reads; what is merged doesn't depend on the order. The classes of a host are aligned in
CLASS_BUCKETS parts, and then those with each other, both in the order of digests. No task gathers a host's pages. Wrappers are
joined to the pages by host, which adaptive execution broadcasts or splits.

Defined results: null pages and pages without main text give the empty text; a page without any tag is one block; tags that
are never closed end with their parent, or where a block starts that can't lie inside them; pages with a null url or without a host form one host; all rows
are extracted, repeated ones too.
"""

from __future__ import annotations

import difflib
import hashlib
import html
import json
import operator
import re
from collections import Counter
from collections.abc import Iterator
from functools import cached_property
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import Scratch, map_batches
from ordwork.llm.url_filter import host_of

LONGEST_GROUP = 8
TEMPLATE_PAGES, TEMPLATE_OF = 3, 8
TEMPLATE_WORDS = 100
CLASS_BUCKETS = 32
#: A task hands on its classes when they have so many elements, and places are forgotten when there are so many.
MOST_HELD = 200_000
#: Parts a text's shape from the number of pages that had the text, that from digests of some of them, and those from the text's digest.
BAR = "\x01"
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(script|style|noscript|template|textarea|svg|iframe)\b[^>]*>.*?(?:</\1\s*>|\Z)|</?[a-zA-Z][^<>]*(?:>|\Z)|[^<]+|<", re.S | re.I)
TAG = re.compile(r"</?([a-zA-Z][a-zA-Z0-9:-]*)")
NAMED = re.compile(r"""\b(?:class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.I)
#: Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
ENDS_WITH_SIBLING = {"li": "li", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "option": "option"}
#: Elements that never hold main text, and words of class, id or role that say the same.
ASIDE = frozenset("nav header footer aside form head title button select option label dialog menu".split())
ASIDE_WORDS = frozenset("ad ads advert advertisement adverts banner sponsor sponsored promo nav navbar navigation menu breadcrumb breadcrumbs header footer masthead sidebar aside widget related cookie cookies consent notice popup modal newsletter subscribe share sharing social comment comments disqus complementary contentinfo search login".split())
#: Elements that class, id and role say nothing against, and first parts of class names that tell of a part elsewhere.
NEVER_ASIDE = frozenset("html body main article".split())
TELLS_OF = frozenset("has have with no not without is".split())
FIRST_SYMBOL = 0xE000


def says_aside(word: str) -> bool:
    """Whether a whole class name, or what it ends with, names a part without main text; `has-sidebar` only tells of one elsewhere."""
    parts = [x for x in re.split(r"[^a-z]+", word) if x]
    return bool(parts) and parts[-1] in ASIDE_WORDS and parts[0] not in TELLS_OF


def marked(tag: str, name: str, by_name: bool = True) -> str:
    """Name of an element in paths: with `!` if it holds no main text, by class, id and role too if by_name."""
    if name in ASIDE:
        return name + "!"
    named = by_name and name not in NEVER_ASIDE and any(says_aside(w) for m in NAMED.finditer(tag) for w in m[1].lower().strip("\"'").split())
    return name + "!" if named else name


class Place:
    """Where in a page: digests of all elements around and of the blocks among them, and what there is to know of them."""

    __slots__ = ("name", "shown", "path", "blocks", "flags", "opened", "closed", "text", "below")

    def __init__(self, above: Place | None, name: str, shown: str):
        self.name, self.shown = name, shown
        self.path = digest(above.path if above else "", shown)
        self.blocks = digest(above.blocks if above else "", shown) if name in BLOCK else above.blocks if above else ""
        flags = set(above.flags if above else "")
        flags |= {f for f, on in (("!", shown[-1:] == "!"), ("m", shown in ("article", "main")), ("p", name == "p")) if on}
        self.flags = "".join(sorted(flags))
        self.opened, self.closed, self.text = (f"{kind}{self.flags}/{self.path}/{self.blocks}/{self.shown}" for kind in "+-#")
        self.below: dict[str, Place] = {}

    def inside(self, name: str, shown: str) -> Place:
        """The place of an element in this one; made once, as pages of one host share most places."""
        found = self.below.get(shown)
        if found is None:
            found = self.below[shown] = Place(self, name, shown)
            ROOT[1] += 1
        return found


def digest(above: str, name: str) -> str:
    return hashlib.blake2b(f"{above}/{name}".encode(), digest_size=6).hexdigest()


#: The place around all others, and the number of places made in it.
ROOT = [Place(None, "", ""), 0]


def flags_of(shape: str) -> str:
    return shape[1 : shape.index("/")]


def tokens(page: str, by_name: bool = True, white_space: bool = False) -> list[tuple[str, str]]:
    """(shape, text): shape is `+place`, `-place` or `#place`; text is empty for tags. Alignment sees no white space outside paragraphs, texts need all of it."""
    if ROOT[1] > MOST_HELD:
        ROOT[:] = [Place(None, "", ""), 0]
    root = ROOT[0]
    stack: list[Place] = []
    is_open: Counter = Counter()
    out = []

    def close(at: int) -> None:
        for x in stack[at:]:
            is_open[x.name] -= 1
        del stack[at:]

    def last(names) -> int | None:
        """Innermost open element of one of the names."""
        if not any(is_open[n] for n in names):
            return None
        return next(k for k in range(len(stack) - 1, -1, -1) if stack[k].name in names)

    for m in TOKEN.finditer(page):
        t = m[0]
        here = stack[-1] if stack else root
        if t[0] != "<" or t == "<":
            shape = here.text
            if t.strip():
                out.append((shape, t))
            elif out and out[-1][0] == shape:
                out[-1] = (shape, out[-1][1] + " ")
            else:
                out.append((shape, " "))
            continue
        if t.startswith(("<!", "<?")) or m[1]:
            continue
        name = TAG.match(t)[1].lower()
        if t[1] == "/":
            at = last((name,))
            if at is not None:
                out.append((stack[at].closed, ""))
                close(at)
            continue
        if name in BLOCK and is_open["p"]:  # an open paragraph ends before a block
            at = next((k for k in range(len(stack) - 1, -1, -1) if stack[k].name in BLOCK), None)
            if at is not None and stack[at].name == "p":
                close(at)
        if name in ENDS_WITH_SIBLING:
            ends = ENDS_WITH_SIBLING[name].split()
            at = last((*ends, "ul", "ol", "dl", "table", "select"))
            if at is not None and stack[at].name in ends:
                close(at)
        here = stack[-1] if stack else root
        if name in VOID or t.endswith("/>"):
            out.append((here.inside(name, name).opened, ""))
            continue
        stack.append(here.inside(name, marked(t, name, by_name)))
        is_open[name] += 1
        out.append((stack[-1].opened, ""))
    return out if white_space else aligned(out)


def aligned(found: list[tuple[str, str]]) -> list[tuple[str, str]]:
    """The tokens that alignment sees: white space counts where it may part inline texts."""
    return [x for x in found if x[0][0] != "#" or x[1].strip() or "p" in flags_of(x[0])]


def squeezed(text: str) -> str:
    return " ".join(html.unescape(text).split())


def named(text: str) -> str:
    """Digest of a squeezed text, or nothing if it is empty."""
    return hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).hexdigest() if text else ""


def first_seen(page: str) -> list[str]:
    """Elements of a wrapper from one page: texts are what one page had."""
    one = hashlib.blake2b(page.encode("utf-8", "surrogatepass"), digest_size=8).hexdigest()
    return [f"{shape}{BAR}1{BAR}{one}{BAR}{had}" if shape[0] == "#" and (had := named(squeezed(text))) else shape for shape, text in tokens(page)]


def meet(x: str, y: str, pages: bool) -> str:
    """One text element for two: the text if they agree (counted together if they are of different pages), else a slot."""
    if BAR not in x and BAR not in y:
        return x
    shape, *a = x.split(BAR)
    _, *b = y.split(BAR)
    if len(a) != 3 or len(b) != 3 or a[2] != b[2]:
        return shape
    n = int(a[0]) + int(b[0]) if pages else max(int(a[0]), int(b[0]))
    # the first few in order are enough to know of TEMPLATE_PAGES different ones, whatever is merged first
    some = a[1] if a[1] == b[1] else ",".join(sorted({*a[1].split(","), *b[1].split(",")})[:TEMPLATE_PAGES])
    return f"{shape}{BAR}{n}{BAR}{some}{BAR}{a[2]}"


def proved(parts: list, pages: int) -> list:
    """parts with texts that too few of the host's pages had as slots, and of other texts only their digests."""
    def one(x):
        if isinstance(x, tuple):
            return (x[0], tuple(proved(x[1], pages)))
        shape, *rest = x.split(BAR)
        known = rest and rest[1].count(",") + 1 >= TEMPLATE_PAGES and int(rest[0]) * TEMPLATE_OF >= pages * TEMPLATE_PAGES
        return f"{shape}{BAR}{rest[2]}" if known else shape

    return [one(x) for x in parts]


# An element of a wrapper is a shape (of a text that is no slot with its pages and itself), or ("+", parts) for a repeated, ("?", parts) for an optional or ("*", shapes) for a free group.


def core(x):
    """What an element is without its quantifiers."""
    while isinstance(x, tuple):
        if x[0] == "*":
            return ("*", *(core(y) for y in x[1]))
        if len(x[1]) > 1:
            return tuple(core(y) for y in x[1])
        x = x[1][0]
    return x.partition(BAR)[0]


def bare(x, quantifiers: set):
    """x without the quantifiers of a single part, which are added to quantifiers; a group of several parts keeps one."""
    while isinstance(x, tuple) and x[0] != "*" and (x[0] == "?" or len(x[1]) == 1):
        quantifiers.add(x[0])
        if len(x[1]) > 1:
            return ("=", x[1])
        x = x[1][0]
    return x


def unite(x, y, pages: bool):
    """The element that stands for both x and y, which have one core; pages: whether they are of different pages."""
    quantifiers: set = set()
    x, y = bare(x, quantifiers), bare(y, quantifiers)
    if isinstance(x, tuple):
        parts = tuple(unite(a, b, pages) for a, b in zip(x[1], y[1], strict=True))
        if x[0] == "*":
            return ("*", parts)
        quantifiers |= {x[0], y[0]} & {"+"}
    else:
        parts = (meet(x, y, pages),)
    out = ("+", parts) if "+" in quantifiers else parts[0] if len(parts) == 1 else None
    if "?" in quantifiers:
        return ("?", parts if out is None else (out,))
    return out if out is not None else ("?", parts)


def fold(parts: list) -> list:
    """Fold neighbouring sequences of one core into repeated groups, short ones first, until nothing folds."""
    cores = [core(x) for x in parts]
    again = True
    while again:
        again = False
        for size in range(1, LONGEST_GROUP + 1):
            if not any(map(operator.eq, cores, cores[size:])):
                continue
            out, i = [], 0
            while i < len(parts):
                n = 1
                if i + size < len(parts) and cores[i] == cores[i + size]:
                    while cores[i : i + size] == cores[i + n * size : i + (n + 1) * size] and len(cores[i : i + size]) == size:
                        n += 1
                if n == 1:
                    out.append(parts[i])
                    i += 1
                    continue
                group = parts[i : i + size]
                for k in range(1, n):
                    group = [unite(a, b, False) for a, b in zip(group, parts[i + k * size : i + (k + 1) * size], strict=True)]
                out.append(group[0] if size == 1 and isinstance(group[0], tuple) and group[0][0] == "*" else ("+", tuple(group)))
                i += n * size
            if len(out) < len(parts):
                parts, cores, again = out, [core(x) for x in out], True
    return parts


def groups_in(parts) -> set[tuple]:
    """Core of every repeated group of several parts."""
    out: set[tuple] = set()
    for x in parts:
        if isinstance(x, tuple) and x[0] != "*":
            out |= groups_in(x[1])
            if len(x[1]) > 1:
                out.add(core(x))
    return out


def gather(parts: list, groups: set[tuple]) -> list:
    """parts with plain sequences turned into the groups that they are one occurrence of, long ones first."""
    cores = [core(x) for x in parts]
    for want in sorted(groups, key=lambda g: (-len(g), repr(g))):
        if want[0] not in cores:
            continue
        out, i = [], 0
        while i < len(parts):
            if cores[i] == want[0] and tuple(cores[i : i + len(want)]) == want:
                out.append(("+", tuple(parts[i : i + len(want)])))
                i += len(want)
            else:
                out.append(parts[i])
                i += 1
        if len(out) < len(parts):
            parts, cores = out, [core(x) for x in out]
    return parts


def align(a: list, b: list) -> list:
    """Wrapper for all that a and b stand for: what only one has becomes optional."""
    most = tally(a) | tally(b)
    groups = groups_in([*a, *b])
    a, b = gather(a, groups), gather(b, groups)
    ka, kb = [repr(core(x)) for x in a], [repr(core(x)) for x in b]
    out = []
    for kind, i, j, k, m in difflib.SequenceMatcher(None, ka, kb, autojunk=False).get_opcodes():
        if kind == "equal":
            out += [unite(x, y, True) for x, y in zip(a[i:j], b[k:m], strict=True)]
        else:
            out += [x if isinstance(x, tuple) and x[0] in "?*" else ("?", (x,)) for x in (*a[i:j], *b[k:m])]
    return freed(fold(out), most)


def tally(parts: list) -> Counter:
    """How often each shape is written in parts."""
    return Counter(x.partition(BAR)[0] for x in shapes_in(parts))


def freed(parts: list, most: Counter) -> list:
    """parts with free groups where a shape is written more often than `most` says: over the two with the fewest parts that every page has, and all between."""
    have = tally(parts)
    if all(n <= most[s] for s, n in have.items()):
        return parts
    parts, inner = [*parts], [tally([x]) for x in parts]
    kept = [not (isinstance(x, tuple) and x[0] in "?*") for x in parts]
    for over in [*have]:
        while have[over] > most[over]:
            at = [i for i, c in enumerate(inner) if over in c]
            upto = [*accumulate(kept, initial=0)]
            first, last = min(zip(at, at[1:]), key=lambda x: (upto[x[1] + 1] - upto[x[0]], x[1] - x[0]), default=(at[0], at[0]))
            span = slice(first, last + 1)
            shapes: dict[str, str] = {}
            for x in shapes_in(parts[span]):
                shapes[s] = meet(shapes[s], x, False) if (s := x.partition(BAR)[0]) in shapes else x
            for c in inner[span]:
                have.subtract(c)
            have.update(shapes.keys())
            parts[span], inner[span], kept[span] = [("*", tuple(shapes[s] for s in sorted(shapes)))], [Counter(shapes.keys())], [False]
    return parts


def shapes_in(parts) -> list[str]:
    return [s for x in parts for s in ([x] if isinstance(x, str) else shapes_in(x[1]))]


class Wrapper:
    """A wrapper with its compiled expression over one character a shape."""

    def __init__(self, parts: list):
        self.parts = parts
        found = shapes_in(parts)
        self.symbols = {s: chr(FIRST_SYMBOL + k) if k < 0x1000 else chr(0x10000 + k) for k, s in enumerate(dict.fromkeys(core(x) for x in found))}
        self.template = frozenset(tuple(x.split(BAR)) for x in found if BAR in x)
        texts = [s for s in self.symbols if s[0] == "#" and "!" not in flags_of(s)]
        inner = [s for s in texts if "m" in flags_of(s)]
        self.main = frozenset(inner or texts)

    @cached_property
    def match(self):
        return re.compile(self.written(self.parts)).fullmatch

    def written(self, parts) -> str:
        # possessive groups keep matching linear; a page they miss is aligned instead
        def one(x) -> str:
            if isinstance(x, str):
                return re.escape(self.symbols[core(x)])
            if x[0] == "*":
                return f"[{self.written(x[1])}]*+"
            return f"(?:{self.written(x[1])})" + ("++" if x[0] == "+" else "?+")

        return "".join(one(x) for x in parts)

    def fits(self, shapes: list[str]) -> bool:
        try:
            return self.match("".join([self.symbols[s] for s in shapes])) is not None
        except KeyError:
            return False


class Classes:
    """Pages that fold alike, merged: (host, digest of what they fold to) -> (number of pages, wrapper parts)."""

    def __init__(self):
        self.found: dict[tuple, tuple[int, list]] = {}
        self.held = 0

    def add(self, host: str | None, page: str) -> None:
        parts = fold(first_seen(page))
        key = hashlib.blake2b(repr([core(x) for x in parts]).encode(), digest_size=12).hexdigest()
        self.merge((host, key), 1, parts)

    def merge(self, key: tuple, n: int, parts: list) -> None:
        if key in self.found:
            m, others = self.found[key]
            self.found[key] = (m + n, [unite(x, y, True) for x, y in zip(others, parts, strict=True)])
        else:
            self.found[key] = (n, parts)
            self.held += len(shapes_in(parts))

    def aligned(self) -> tuple[int, list]:
        """Number of pages and wrapper parts of all classes, aligned in the order of their keys."""
        n, parts = 0, None
        for key in sorted(self.found):
            m, others = self.found[key]
            n, parts = n + m, others if parts is None else align(parts, others)
        return n, parts or []


def infer(pages: list[str]) -> list:
    """Wrapper parts from pages of one host; equal pages count once."""
    classes = Classes()
    for page in dict.fromkeys(pages):
        classes.add("", page)
    n, parts = classes.aligned()
    return proved(parts, n)


def extract(page: str, wrapper: Wrapper) -> str:
    """Texts in the main slots of the wrapper, or of the wrapper generalised for this page; where that gives nothing, marks by class, id and role are left out."""
    return extracted(page, wrapper, True) or extracted(page, wrapper, False)


def extracted(page: str, wrapper: Wrapper, by_name: bool) -> str:
    found = tokens(page, by_name, white_space=True)
    shapes = [s for s, _ in aligned(found)]
    template = wrapper.template
    if not wrapper.fits(shapes):
        wrapper = Wrapper(align(wrapper.parts, fold(shapes)))
    if wrapper.main.isdisjoint(shapes):  # the host's main part is missing here, though the page may fit: judged by its own shapes
        wrapper = Wrapper(fold(shapes))
    if template:
        texts = [(s, squeezed(t)) for s, t in found if s in wrapper.main]
        removed = sum(len(t.split()) for s, t in texts if (s, named(t)) in template)
        left = sum(len(t.split()) for _, t in texts) - removed
        if not left or removed > max(left, TEMPLATE_WORDS):
            template = frozenset()
    blocks, now, at = [], [], None
    for shape, text in found:
        if shape[0] != "#":
            name = shape.rpartition("/")[2].rstrip("!")
            if name in BLOCK:
                blocks.append(now)
                now = []
            elif name == "br":
                now.append(" ")
        elif not text.strip() and "!" not in flags_of(shape):  # parts inline texts, whatever is main
            now.append(" ")
        elif shape in wrapper.main and not (template and (shape, named(squeezed(text))) in template):
            place = shape.split("/")[2]
            if "".join(now).strip() and place != at:
                blocks.append(now)
                now = []
            at = place
            now.append(text)
    blocks.append(now)
    joined = (squeezed("".join(b)) for b in blocks)
    return "\n".join(b for b in joined if b)


def wrappers(pages: DataFrame, url: str = "url", page: str = "html") -> DataFrame:
    """(host, wrapper): the wrapper of each host, from all its pages, as JSON."""
    rows = pages.where(F.col(page).isNotNull()).select(host_of(F.col(url)).alias("host"), F.col(page).alias("page"))

    def merge_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classes = Classes()

        def taken() -> pa.RecordBatch:
            found = [(host, key, n, json.dumps(parts)) for (host, key), (n, parts) in classes.found.items()]
            return pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*found, strict=True), (pa.string(), pa.string(), pa.int64(), pa.string()), strict=True)], names=["host", "key", "n", "parts"])

        for batch in batches:
            for host, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                classes.add(host, text.as_py())
                if classes.held > MOST_HELD:
                    yield taken()
                    classes = Classes()
        if classes.found:
            yield taken()

    def align_part(frame):
        classes = Classes()
        for key, n, parts in zip(frame["key"], frame["n"], frame["parts"], strict=True):
            classes.merge((key,), int(n), parts_of(parts))
        n, parts = classes.aligned()
        return frame.head(1).assign(n=n, parts=json.dumps(parts))[["host", "bucket", "n", "parts"]]

    def align_host(frame):
        n, parts = 0, None
        for m, others in frame.sort_values("bucket")[["n", "parts"]].itertuples(index=False):
            n, parts = n + int(m), parts_of(others) if parts is None else align(parts, parts_of(others))
        return frame.head(1).assign(wrapper=json.dumps(proved(parts, n)))[["host", "wrapper"]]

    classes = rows.mapInArrow(merge_task, "host string, key string, n long, parts string").withColumn("bucket", F.pmod(F.xxhash64("key"), F.lit(CLASS_BUCKETS)))
    # by number, as adaptive execution would put these few rows with much work each into one task
    tasks = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = classes.repartition(tasks, "host", "bucket").groupBy("host", "bucket").applyInPandas(align_part, "host string, bucket long, n long, parts string")
    return parts.repartition(tasks, "host").groupBy("host").applyInPandas(align_host, "host string, wrapper string")


def parts_of(text: str) -> list:
    group = lambda x: x if isinstance(x, str) else (x[0], tuple(group(y) for y in x[1]))
    return [group(x) for x in json.loads(text)]


def loaded(text: str | None) -> Wrapper:
    return Wrapper(parts_of(text or "[]"))


def main_text(pages: DataFrame, url: str = "url", page: str = "html", key: str = "page_id") -> DataFrame:
    """key, url and text of every page."""
    found = Scratch(pages.sparkSession, "wrappers").save(wrappers(pages, url, page), "wrappers")
    rows = pages.select(F.col(key).alias("key"), F.col(url).alias("url"), F.col(page).alias("page"), host_of(F.col(url)).alias("host"))
    joined = rows.join(found, "host", "left").select("key", "url", "page", "wrapper")
    kind = dict(pages.dtypes)[key]

    def each(batch):
        kept: dict = {}
        out = []
        for text, wrapper in zip(batch.column(2), batch.column(3).to_pylist(), strict=True):
            if wrapper not in kept:
                kept[wrapper] = loaded(wrapper)
            out.append(extract(text.as_py() or "", kept[wrapper]))
        yield {"key": batch.column(0), "url": batch.column(1), "text": out}

    return map_batches(joined, each, f"key {kind}, url string, text string").withColumnsRenamed({"key": key, "url": url})
