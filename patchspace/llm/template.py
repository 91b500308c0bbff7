"""Main text of HTML pages through templates deduced per host.

1. Pages are cut into tokens: tags with their class and id, and text blocks. For each host and
   token the pages add up ``n_pages``, the total count and a fingerprint, the sum of a hash of
   (page, count in the page). Equal sums mean equal occurrence vectors, so vectors are compared
   without being built, and sums combine before the shuffle however large a host is. Start tags
   also add up where their element begins and ends, how much text it holds (links and declared
   parts apart), the least and largest hash of that text, and which of 64 hash values the rest of
   the page had.
2. Tokens of a host with equal vectors form an equivalence class. A class is valid if it is
   large and frequent: at least ``min_size`` tokens, one occurrence a page, on at least
   ``min_share`` of at least ``min_pages`` pages. Classes are nested by the mean places of their
   tokens: a class lies in the slot of the parent whose bounding tokens enclose it; one that
   straddles its parent's tokens is left out.
3. The start tags of valid classes are the template's elements. From the page as a whole the
   deduction descends into the element that holds at least ``HOLDS`` of the text of all pages, as
   long as there is one, and ends at an article or main element at the latest: the slots of that
   element are the content. An element or text block that is the same on all its pages, while the
   rest of those pages takes ``CONTEXTS`` or more values, is fixed (its slots are empty of data). Fixed
   elements go, inside the content as well; fixed blocks go outside article and main elements, as
   inside them a block on most pages of a host can be a passage that its articles share.
4. On a page with its host's content element the text of that element's slots is kept, less fixed
   elements and less what markup declares as menu, header, footer, sidebar, notice, advert, form or
   comments. Tag and name lists alone decide on pages without that element and on hosts without a
   template (fewer than ``min_pages`` pages), and where the template would leave nothing: text in an
   article or main element is kept, or, without any, all text outside declared parts that is not
   a fixed block of the host. Every element is closed by its own end tag, by its parent's, or by a start tag that
   implies its end; class and id words count on containers only.

Inside kept slots nothing is dropped. References are decoded, white space within a block
becomes one space, blocks are joined by one newline. Null or empty HTML gives an empty text;
a null url belongs to a host of its own; repeated rows count as pages of their own.
"""

from __future__ import annotations

import html as html_lib
import json
import re

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import ship, staged

TOKEN = re.compile(r"<!--.*?(?:-->|$)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>", re.S)
RAW = {t: re.compile(rf"</{t}\s*>", re.I) for t in ("script", "style", "textarea", "title", "noscript", "iframe", "template", "svg", "xmp")}
ATTRIBUTE = re.compile(r"""([^\s"'>/=]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"']+))?""")
# Elements that end a run of text, and elements that never hold the article.
BLOCK = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
OUT = frozenset("head title script style noscript iframe template svg nav footer aside form button select option textarea input label dialog menu object canvas audio video map".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
MAIN = frozenset(("article", "main"))
AWAY = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|adsense|sponsor\w*|promo\w*|banner|nav\w*|menu\w*|breadcrumbs?|side-?bar\w*|footer|header|masthead|cookies?|consent|gdpr|notices?|alert|popup|modal|overlay|newsletter|subscribe|subscription|sign-?up|login|comments?|commentlist|disqus|replies|reply|respond|shar(?:e|ing)|social|related|recommend\w*|pagination|pager|toolbar|search\w*|widget|navigation|contentinfo|complementary|dialog)(?:$|[\s_-])", re.I)
# Class and id words tell of containers only; an id of a section is often an anchor, so all of its words count.
CONTAINERS = frozenset("div section aside nav header footer form fieldset ul ol dl table details dialog menu figure".split())
NEVER_AWAY = frozenset("article main h1 h2 h3 h4 h5 h6 hgroup".split())
MASK = (1 << 62) - 1
FP_BITS = 38  # sums of the fingerprints of 2**25 pages stay within a long
HOLDS, CONTEXTS = 0.5, 3


def tokens(page: str):
    """Yields ("text", string) and ("tag", closing?, name, key, away?) in page order."""
    at, n = 0, len(page)
    while at < n:
        m = TOKEN.search(page, at)
        if m is None:
            yield ("text", page[at:])
            return
        if m.start() > at:
            yield ("text", page[at : m.start()])
        at = m.end()
        name = m[2] or m[5]
        if not name:
            continue
        name = name.lower()
        closing, attrs = bool(m[1] or m[4]), m[3] or m[6] or ""
        key, away = name, False
        if not closing and ("=" in attrs or "hidden" in attrs):
            marks = []
            for k, v in ATTRIBUTE.findall(attrs):
                k, v = k.lower(), v.strip("\"'")
                if k == "hidden":
                    away = away or v.lower() not in ("until-found",)
                elif k in ("class", "id", "role"):
                    marks.append(v)
                    away = away or declared(name, k, v)
            if marks:
                key = f"{name}.{' '.join(marks)}"
        yield ("tag", closing, name, key, away)
        if not closing and name in RAW and not attrs.endswith("/"):
            end = RAW[name].search(page, at)
            at = end.start() if end else n


def declared(name: str, attribute: str, value: str) -> bool:
    """Whether a class, id or role says that an element is no part of the article."""
    if name in NEVER_AWAY or attribute != "role" and name not in CONTAINERS:
        return False
    if name == "section" and attribute == "id":
        words = re.split(r"[\s_-]+", value.strip())
        return bool(AWAY.fullmatch(value.strip())) or all(AWAY.fullmatch(w) for w in words)
    return bool(AWAY.search(value))


def text_key(words: str) -> str:
    return "#" + xxhash.xxh64_hexdigest(words)


class Seen:
    """What a page tells of one token: its count, first place, and of an element its end and text."""

    __slots__ = ("chars", "content", "count", "end", "first")

    def __init__(self, first: int):
        self.count, self.first, self.end, self.chars, self.content = 0, first, first, 0, 0


def token_counts(page: str) -> tuple[dict[str, Seen], Seen]:
    """Each token of the page, and the page as a whole. ``chars`` leaves out links and declared parts."""
    found: dict[str, Seen] = {}
    whole = Seen(-1)
    elements = Elements()
    links = place = 0
    for t in tokens(page):
        if t[0] == "text":
            words = " ".join(t[1].split())
            if not words:
                continue
            key = text_key(words)
            content, chars = int(key[1:], 16) >> 2, 0 if links or elements.away else len(words)
            for up in (*(e[3] for e in elements.open if e[3] is not None), whole):
                up.content = (up.content + content) & MASK
                up.chars += chars
            own = found.setdefault(key, Seen(place))
            own.content, own.chars = content, len(words)
        else:
            _, closing, name, tag, away = t
            key = ("</" if closing else "<") + tag
            if name == "a":
                links = 0 if closing else 1
        seen = found.setdefault(key, Seen(place))
        seen.count += 1
        if t[0] == "tag":
            for e in elements.step(closing, name, away, seen if not closing and seen.count == 1 else None):
                if e[3] is not None:
                    e[3].end = place
        place += 1
    for e in elements.open:
        if e[3] is not None:
            e[3].end = place
    whole.end = place
    return found, whole


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def _pages(pages: DataFrame, id_col: str, url_col: str, html_col: str) -> DataFrame:
    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), host_of(F.col(url_col)).alias("host"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))


SUMS = ("n_pages", "total", "fingerprint", "places", "ends", "chars")


def occurrences(rows: DataFrame) -> DataFrame:
    """host, token, n_pages, total, fingerprint, places, ends, chars: sums over the pages of a host;
    lo, hi, contexts: extremes of the hash of an element's text, and 64 bits of the rest's hashes.

    A task sums what it has read before the shuffle; tokens that a host's pages do not share
    still cost a row each, but are only hashes. The token '' stands for the page.
    """
    ship(rows.sparkSession)
    kinds = (pa.string(), pa.string(), *[pa.int64()] * 3, *[pa.float64()] * 2, *[pa.int64()] * 4)
    names = ["host", "token", *SUMS, "lo", "hi", "contexts"]
    ddl = "host string, token string, n_pages long, total long, fingerprint long, places double, ends double, chars long, lo long, hi long, contexts long"

    def count(batches):
        for batch in batches:
            sums: dict[tuple[str, str], list] = {}
            for pid, host, page in zip(batch.column("page_id").to_pylist(), batch.column("host").to_pylist(), batch.column("html").to_pylist(), strict=True):
                found, whole = token_counts(page)
                whole.count = 1
                salt = xxhash.xxh64_intdigest(f"{pid}")
                for key, t in (("", whole), *found.items()):
                    rest = 1 << ((whole.content - t.content) * 0x9E3779B97F4A7C15 >> 20 & 63)
                    s = sums.get((host, key))
                    if s is None:
                        s = sums[host, key] = [0, 0, 0, 0.0, 0.0, 0, t.content, t.content, 0]
                    s[0] += 1
                    s[1] += t.count
                    s[2] += (salt * (2 * t.count + 1) & 0xFFFFFFFFFFFFFFFF) >> (64 - FP_BITS)
                    s[3] += t.first
                    s[4] += t.end
                    s[5] += t.chars
                    s[6], s[7] = min(s[6], t.content), max(s[7], t.content)
                    s[8] |= rest
            cols = [[k[0] for k in sums], [k[1] for k in sums], *([v[i] for v in sums.values()] for i in range(8)), [v[8] - (1 << 64) if v[8] >> 63 else v[8] for v in sums.values()]]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=names)

    sums = rows.select("page_id", "host", "html").mapInArrow(count, ddl)
    return sums.groupBy("host", "token").agg(*[F.sum(c).alias(c) for c in SUMS], F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.bit_or("contexts").alias("contexts"))


def deduce(occ: DataFrame, min_pages: int = 3, min_share: float = 0.5, min_size: int = 3) -> DataFrame:
    """host, template: the valid classes, nested, and what they make of the page, as JSON; hosts without
    a valid class have no row.

    Only tokens that fill ``min_share`` of a host's pages once each reach the grouping by host,
    so a group is as large as one page's frame.
    """
    ship(occ.sparkSession)
    sizes = occ.where("token = ''").select(F.col("host").alias("h"), F.col("n_pages").alias("pages"), F.col("chars").alias("all_chars")).where(F.col("pages") >= min_pages)
    often = occ.where("token <> '' AND total = n_pages").join(sizes, F.col("host") == F.col("h")).where(F.col("n_pages") >= min_share * F.col("pages"))
    fixed = (F.col("lo") == F.col("hi")) & (F.col("chars") > 0) & (F.bit_count("contexts") >= CONTEXTS)
    member = F.struct((F.col("places") / F.col("n_pages")).alias("place"), "token", (F.col("ends") / F.col("n_pages")).alias("end"), "chars", fixed.alias("fixed"))
    cls = often.groupBy("host", "n_pages", "fingerprint").agg(F.max("all_chars").alias("all_chars"), F.collect_list(member).alias("members")).where(F.size("members") >= min_size)
    per_host = cls.groupBy("host").agg(F.max("all_chars").alias("all_chars"), F.collect_list(F.struct("n_pages", F.array_sort("members").alias("members"))).alias("classes"))

    def build(classes, all_chars):
        found = nested([(c.n_pages, [tuple(m) for m in c.members]) for c in classes])
        return json.dumps({"classes": found} | verdict(found, all_chars))

    return per_host.select("host", F.udf(build, "string")("classes", "all_chars").alias("template"))


def verdict(classes: list[dict], all_chars: int) -> dict:
    """The element whose slots are the content (null if none holds enough), and the fixed elements."""
    elements = [(place, end, token, chars) for c in classes for place, token, end, chars in zip(c["places"], c["tokens"], c["ends"], c["chars"], strict=True) if token[0] == "<" and token[1] != "/"]
    at, until, held, main = -1.0, float("inf"), all_chars, None
    while main is None or re.match(r"<(article|main)(\.|$)", main) is None:
        inner = [(chars, -place, -end, token) for place, end, token, chars in elements if at < place and end <= until and chars >= HOLDS * held and chars > 0]
        if not inner:
            break
        held, place, end, main = max(inner)
        at, until = -place, -end
    return {"main": main, "fixed": [t for c in classes for t, f in zip(c["tokens"], c["fixed"], strict=True) if f and t[0] == "<" and t != main]}


def nested(classes: list[tuple[int, list[tuple]]]) -> list[dict]:
    """Classes by falling support; each names its parent and the slot of it that holds it.

    Members are (place, token, end, chars, fixed). A class that straddles a bounding token of the
    class above it is not properly nested and is left out.
    """
    out: list[dict] = []
    for n, members in sorted(classes, key=lambda c: (-c[0], -len(c[1]), c[1][0][:2])):
        places = [m[0] for m in members]
        parent = slot = None
        valid = True
        for i, up in enumerate(out):
            inside = {sum(p > q for q in up["places"]) for p in places}
            if len(inside) == 1:
                parent, slot = i, inside.pop()
            elif n < up["n_pages"]:
                valid = False
                break
        if valid:
            _, tokens_, ends, chars, fixed = zip(*members, strict=True)
            out.append({"n_pages": n, "places": places, "tokens": list(tokens_), "ends": list(ends), "chars": list(chars), "fixed": list(fixed), "parent": parent, "slot": slot})
    return out


class Frame:
    """A host's template as the extraction uses it: content element, fixed elements, fixed wording."""

    def __init__(self, template: str | None):
        t = json.loads(template) if template else {"classes": [], "main": None, "fixed": []}
        self.texts = {x for c in t["classes"] for x, f in zip(c["tokens"], c["fixed"], strict=True) if f and x[0] == "#"}
        self.main, self.fixed = t["main"], frozenset(t["fixed"])


SECTION = frozenset("article main section div aside nav header footer form body table ul ol dl fieldset details dialog menu figure head html".split())
# Start tags that end an open element of a name, looked for up to the nearest bounding element.
P_ENDERS = BLOCK - frozenset("br caption dd dt legend li option head body html tbody td tfoot th thead tr".split())
ENDS = {
    "li": ("li",), "dd": ("dd", "dt"), "dt": ("dd", "dt"), "option": ("option",), "optgroup": ("option", "optgroup"),
    "td": ("td", "th"), "th": ("td", "th"), "tr": ("td", "th", "tr"),
    "tbody": ("td", "th", "tr", "thead", "tbody", "tfoot"), "tfoot": ("td", "th", "tr", "thead", "tbody"), "body": ("head",),
} | {t: ("p",) for t in P_ENDERS}


class Elements:
    """The open elements of a page: (name, away, in an article or main element, own)."""

    def __init__(self):
        self.open: list[tuple[str, bool, bool, object]] = []

    @property
    def away(self) -> bool:
        return bool(self.open) and self.open[-1][1]

    @property
    def inside(self) -> bool:
        return bool(self.open) and self.open[-1][2]

    def close(self, names: tuple[str, ...]) -> list[tuple]:
        """End the open elements of these names; of small elements, only those within the nearest section."""
        section = not names or names[0] in SECTION or names[0] in OUT
        i, gone = len(self.open) - 1, []
        while names and i >= 0:
            if self.open[i][0] in names:
                gone += self.open[i:]
                del self.open[i:]
                if len(names) == 1:
                    break
            elif not section and self.open[i][0] in SECTION:
                break
            i -= 1
        return gone

    def step(self, closing: bool, name: str, declared_away: bool, own: object = None) -> list[tuple]:
        """Take a tag; returns the elements that it ended."""
        if name in VOID:
            return []
        if closing:
            return self.close((name,))
        gone = self.close(ENDS.get(name, ()))
        up_away, up_in = self.away, self.inside
        if name in MAIN and not declared_away:
            self.open.append((name, up_away and up_in, True, own))  # comments may hold articles
        else:
            out = declared_away and name not in ("html", "body") or name in OUT or name == "header" and not up_in
            self.open.append((name, up_away or out, up_in, own))
        return gone


def extract(page: str, frame: Frame) -> str:
    """The main text of one page under the template of its host."""
    slots: list[tuple[bool, bool, bool, bool, str]] = []
    elements = Elements()
    text: list[str] = []
    any_main = False
    content = fixed = 0  # open elements that the template calls content, or fixed wording

    def flush() -> None:
        if text:
            raw = "".join(text)
            words = " ".join(html_lib.unescape(raw).split())
            if words:
                wording = bool(frame.texts) and text_key(" ".join(raw.split())) in frame.texts
                slots.append((elements.inside, content > 0, fixed > 0, wording, words))
            text.clear()

    for t in tokens(page):
        if t[0] == "text":
            if not elements.away:
                text.append(t[1])
            continue
        _, closing, name, tag, own_away = t
        own = None
        if not closing and name not in VOID:
            own = 1 if "<" + tag == frame.main else 2 if "<" + tag in frame.fixed else None
        if name in BLOCK or own:
            flush()
        elif closing and fixed and elements.open and elements.open[-1][3] == 2:
            flush()
        any_main = any_main or not closing and name in MAIN and not own_away
        gone = elements.step(closing, name, own_away, own)
        content += (own == 1) - sum(e[3] == 1 for e in gone)
        fixed += (own == 2) - sum(e[3] == 2 for e in gone)
    flush()
    if any(c for _, c, _, _, _ in slots):
        articles = any(c and i for i, c, _, _, _ in slots)
        kept = [b for i, c, f, wording, b in slots if c and not f and (i or not articles and not wording)]
        if kept:
            return "\n".join(kept)
    if any_main:
        return "\n".join(b for i, _, _, _, b in slots if i)
    return "\n".join(b for _, _, _, wording, b in slots if not wording)


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_pages: int = 3, min_share: float = 0.5, min_size: int = 3) -> DataFrame:
    """page_id, url, text, n_chars for every page."""
    ship(pages.sparkSession)
    rows = _pages(pages, id_col, url_col, html_col)
    templates = staged(deduce(occurrences(rows), min_pages, min_share, min_size).withColumnRenamed("host", "_host"), "templates")

    def read(batches):
        frames: dict[str | None, Frame] = {}
        for batch in batches:
            out = []
            for page, template in zip(batch.column("html").to_pylist(), batch.column("template").to_pylist(), strict=True):
                if template not in frames:
                    if len(frames) > 10_000:
                        frames.clear()
                    frames[template] = Frame(template)
                out.append(extract(page, frames[template]))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(out, pa.string()), pa.array([len(x) for x in out], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    joined = rows.join(templates, F.col("host") == F.col("_host"), "left").select("page_id", "url", "html", "template")
    return joined.mapInArrow(read, "page_id long, url string, text string, n_chars long")


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
