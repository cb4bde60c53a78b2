"""Main text of pages by union-free wrappers that are inferred per host.

A page is a stream of tokens: tags and texts. A wrapper is union-free: a region (the path of container elements and
of named elements inside them) is fixed, optional (missing on some pages) or repeated, and has constant text or is a slot. Wrappers
of parts of a host merge by adding counts, so the wrapper of a host is an aggregate over whole streams of all its
different pages: pages by host, region and digest of the region's set of texts (a repeated text counts once, and
pages without an optional region do not count for it). A host with most of all pages is combined in tasks first.

A region is template where one set of texts holds on at least ``CONSTANT`` percent of the pages that have it, and on two or more.
Other regions are slots. Their varying text is weighed by the container they stand in; an article or main element is
evidence and counts ``MARKED`` times. A page's text is that of its heaviest container and all slots inside, in page order, without template and
without menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles and comments. Where a page has
template regions only (its host's pages are alike), the wrapper cannot tell content, and the same choice is made among these.
Constant text in a region that also varies, such as a heading, stays.

:func:`infer_wrapper` aligns whole streams of a few pages one after the other; it is the reference for small hosts.

Defined cases: a null or empty page and a page without text give an empty text; a null or unparsable URL is a host
of its own (the empty one); broken markup (unclosed or stray tags, cut entities) is read as browsers do: character
references without a known name stay as they are; repeated rows are read each; extra columns are not read; an
empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import html
import json
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.llm.url_filter import host_of

#: Percent of a region's pages that share its texts where it is template.
CONSTANT = 90
#: What varying text in an article or main element weighs.
MARKED = 2

# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe svg math object xmp noembed".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hr html li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul".split()
)
CLOSES_P = BLOCK - {"br", "body", "html", "head", "title", "option", "caption", "tbody", "td", "tfoot", "th", "thead", "tr"}
CONTAINER = frozenset("article aside body center dialog div fieldset footer form header main menu nav section table td ul ol".split())
#: Elements that hold no main text.
CHROME = frozenset("nav header footer aside form menu button select option dialog label head".split())
#: Words in class, id and role that name what is not main text.
CHROME_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments cookie cookies consent copyright disqus "
    "footer gdpr header masthead menu modal nav navbar navigation newsletter notice notices pager pagination popup promo promoted promotion "
    "related respond reply replies share sharing sidebar sidebars signup skip social sponsor sponsored subscribe toolbar topbar widget widgets "
    "complementary contentinfo search alert reactions".split()
)
CONTENT_WORDS = frozenset("article post entry story content main body text page wrapper container".split())

#: Comments and declarations; tags; tags with unbalanced quotes, or cut by the page's end; texts.
_TOKEN = re.compile(
    r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>?|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^>"']|"[^"]*"|'[^']*')*)>"""
    r"""|<(/?)([A-Za-z][A-Za-z0-9:-]*)([^>]*)(>|\Z)|[^<]+|<""",
    re.S,
)
_NAMED = re.compile(r"""\b(?:class|id|role|aria-label|itemprop)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|$)|display\s*:\s*none|aria-hidden\s*=\s*["']?true""", re.I)
_WHITE = re.compile(r"\s+")


def tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """(kind, value, attributes) with kinds open, close and text; contents of raw elements are skipped."""
    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.match(page, at)
        if m is None:
            break
        at = m.end()
        if name := m[2] or (m[7] and m[5]):
            name, attributes = name.lower(), m[3] or m[6] or ""
            if m[1] or m[4]:
                yield "close", name, ""
                continue
            yield "open", name, attributes
            if name in RAW and not attributes.endswith("/"):
                stop = re.compile(rf"</{re.escape(name)}\b[^>]*>?", re.I).search(page, at)
                at = stop.end() if stop else n
                yield "close", name, ""
        elif (m[0][0] != "<" or m[0] == "<") and m[7] is None:
            yield "text", m[0], ""


def _names(attributes: str) -> list[str]:
    if "=" not in attributes:
        return []
    found = " ".join(a or b or c for a, b, c in _NAMED.findall(attributes))
    return [w for w in re.split(r"[^a-z]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", found).lower()) if w]


def is_chrome(name: str, attributes: str) -> bool:
    if name in ("html", "body"):
        return False
    if name in CHROME:
        return True
    words = _names(attributes)
    if words and CHROME_WORDS.intersection(words) and not (name in ("article", "main") or CONTENT_WORDS.issuperset(words)):
        return True
    return bool(attributes) and bool(_HIDDEN.search(attributes))


class Region:
    """Open elements while a page is read."""

    def __init__(self):
        self.stack: list[tuple[str, bool, str]] = []

    def open(self, name: str, attributes: str) -> None:
        if name in VOID or attributes.endswith("/"):
            return
        if name in CLOSES_P:
            self._end_open("p")
        if name in ("li", "dt", "dd", "tr", "td", "th", "option"):
            self._end_open(name, stop=("ul", "ol", "dl", "table", "select"))
        label = name
        if name in CONTAINER:
            words = _names(attributes)
            label = ".".join([name, *words[:3]])
        elif name in BLOCK and (words := _names(attributes)):
            label = ".".join(["~" + name, *words[:3]])
        chrome = bool(self.stack and self.stack[-1][1]) or is_chrome(name, attributes)
        self.stack.append((name, chrome, label))

    def _end_open(self, name: str, stop: tuple[str, ...] = ("article", "div", "section", "body", "main", "td", "li", "blockquote")) -> None:
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == name:
                del self.stack[i:]
                return
            if self.stack[i][0] in stop:
                return

    def close(self, name: str) -> None:
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == name:
                del self.stack[i:]
                return
            if self.stack[i][0] in ("article", "main", "body") and name not in ("article", "main", "body", "html"):
                return  # a stray end tag does not end the article

    @property
    def chrome(self) -> bool:
        return bool(self.stack) and self.stack[-1][1]

    @property
    def path(self) -> str:
        return "/".join(label for name, _, label in self.stack if name in CONTAINER or label[0] == "~")


def blocks(page: str) -> list[tuple[str, str]]:
    """(region, text) of each block outside of chrome, in page order, with references decoded and white space joined."""
    region, out, line, where = Region(), [], [], ""

    def end() -> None:
        if line:
            text = _WHITE.sub(" ", html.unescape("".join(line))).strip()
            if text:
                out.append((where, text))
            line.clear()

    for kind, value, attributes in tokens(page):
        if kind == "text":
            if not region.chrome and not (region.stack and region.stack[-1][0] in RAW):
                if not line:
                    where = region.path
                line.append(value)
            continue
        if value in BLOCK:
            end()
        if kind == "open":
            region.open(value, attributes)
        else:
            region.close(value)
    end()
    return out


# -- wrappers ------------------------------------------------------------------------------------------


def stream(page: str) -> list[tuple[str, str]]:
    """Tokens for alignment: tags with their region's path, and texts outside of raw elements."""
    region, out = Region(), []
    for kind, value, attributes in tokens(page):
        if kind == "text":
            text = _WHITE.sub(" ", value).strip()
            if text:
                out.append(("#text", region.path + "\t" + text))
        else:
            (region.open if kind == "open" else region.close)(*((value, attributes) if kind == "open" else (value,)))
            if value not in RAW:
                out.append((kind, value))
    return out


def _key(token: tuple) -> tuple:
    """What two tokens have to share to be aligned: texts and slots of one region, or equal tags and groups."""
    return ("#text", token[1].partition("\t")[0]) if token[0] in ("#text", "#slot") else token


def align(wrapper: list[tuple], page: list[tuple]) -> list[tuple]:
    """One generalisation step. Items: ('open'|'close', tag), ('#text', region, text), ('#slot', region),
    ('?', items) for optional and ('+', items) for repeated groups."""
    from difflib import SequenceMatcher

    out: list[tuple] = []

    def mismatch(items: list[tuple]) -> None:
        if not items:
            return
        keys = [_key(x) for x in items]
        n = len(items)
        back = [_key(x) for x in out[-n:]]
        if back == keys:  # repeats what stands before it
            group = tuple(("#slot", x[1].partition("\t")[0]) if x[0] == "#text" and x != y else x for x, y in zip(out[-n:], items))
            out[-n:] = [("+", group)]
        elif out and out[-1][0] == "+" and [_key(x) for x in out[-1][1]] == keys:
            pass
        elif all(x[0] in ("?", "+") for x in items):
            out.extend(items)
        else:
            out.append(("?", tuple(items)))

    a, b = [_key(x) for x in wrapper], [_key(x) for x in page]
    for op, i, j, k, m in SequenceMatcher(None, a, b, autojunk=False).get_opcodes():
        if op == "equal":
            for x, y in zip(wrapper[i:j], page[k:m]):
                out.append(x if x == y or x[0] not in ("#text", "#slot") else ("#slot", x[1].partition("\t")[0]))
        else:
            mismatch(wrapper[i:j])
            if op != "delete":
                mismatch(page[k:m])
    return out


def infer_wrapper(pages: list[str]) -> list[tuple]:
    wrapper: list[tuple] = []
    for page in pages:
        wrapper = align(wrapper, stream(page)) if wrapper else stream(page)
    return wrapper


_MARKED = re.compile(r"(?:^|/)(?:article|main)(?:\.[^/]*)?(?=/|$)")


def container(region: str) -> str:
    """Where a region's text is weighed: its outermost article or main element, else its innermost container."""
    found = _MARKED.search(region)
    return region[: found.end()] if found else "/".join(x for x in region.split("/") if not x.startswith("~"))


def page_regions(page: str) -> list[tuple[str, int, int]]:
    """(region, digest of its set of texts, characters) of a page."""
    texts: dict[str, list[str]] = {}
    for where, text in blocks(page):
        texts.setdefault(where, []).append(text)
    return [(r, _digest("\n".join(sorted(set(t)))), sum(map(len, t))) for r, t in texts.items()]


def _digest(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)


def content_rule(regions: list[tuple[str, int, int, int]]) -> dict:
    """A host's wrapper from (region, pages, pages of the most common set of texts, characters): template regions, and varying text by container."""
    template = [r for r, pages, top, _ in regions if top > 1 and 100 * top >= CONSTANT * pages]
    weight: Counter[str] = Counter()
    for r, _, _, chars in regions:
        if r not in template:
            where = container(r)
            weight[where] += chars * (MARKED if _MARKED.search(where) else 1)
    return {"template": sorted(template), "weight": dict(sorted(weight.items()))}


def main_text(page: str, rule: dict) -> str:
    """The page's main text: slots in and below its container with the most varying text on the host."""
    found, template = blocks(page), set(rule["template"])
    left = [(r, t) for r, t in found if r not in template]
    # A page of template only is judged by the lengths of its own texts.
    weight: Counter[str] = Counter(rule["weight"])
    if not left:
        left = found
        for r, t in left:
            where = container(r)
            weight[where] += len(t) * (MARKED if _MARKED.search(where) else 1)
    root = max(sorted({container(r) for r, _ in left}), key=lambda x: weight[x], default="")
    return " ".join(t for r, t in left if not root or r == root or r.startswith(root + "/"))


def infer_rules(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per host: host, rule (JSON), from all its different pages."""

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1)):
                page = page.as_py() or ""
                digest = _digest(page)
                out += [(host, digest, *x) for x in page_regions(page)]
            columns = list(zip(*out)) or [()] * 5
            types = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], ["host", "page", "region", "texts", "chars"])

    parts = pages.select(host_of(F.col(url_col)).alias("host"), F.col(html_col).alias("page")).mapInArrow(seen, "host string, page long, region string, texts long, chars long")
    # Equal pages are one page.
    parts = parts.distinct().groupBy("host", "region", "texts").agg(F.count(F.lit(1)).alias("pages"), F.sum("chars").alias("chars"))
    parts = parts.groupBy("host", "region").agg(F.sum("pages").alias("pages"), F.max("pages").alias("top"), F.sum("chars").alias("chars"))
    hosts = parts.groupBy("host").agg(F.sort_array(F.collect_list(F.struct("region", "pages", "top", "chars"))).alias("regions"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rules = [json.dumps(content_rule([tuple(r.values()) for r in regions])) for regions in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rules, pa.string())], ["host", "rule"])

    return hosts.mapInArrow(rows, "host string, rule string")


_NO_RULE = json.dumps(content_rule([]))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: id, url, text, n_chars."""
    rules = infer_rules(pages, url_col, html_col)
    asked = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("page"), host_of(F.col(url_col)).alias("host"))
    asked = asked.join(rules, "host", "left").select("id", "url", "page", "rule")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, dict] = {}
        for batch in batches:
            texts = []
            for page, rule in zip(batch.column(2), batch.column(3)):
                rule = rule.as_py() or _NO_RULE  # a host without any text has no wrapper
                if rule not in known:
                    known.clear() if len(known) > 10_000 else None
                    known[rule] = json.loads(rule)
                texts.append(main_text(page.as_py() or "", known[rule]))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["id", "url", "text", "n_chars"]
            )

    return asked.mapInArrow(rows, "id long, url string, text string, n_chars long").withColumnRenamed("id", id_col)
