"""Main text of web pages by maximum-scoring subsequence.

A page is a sequence of words and tags. Words score positive and tags negative; the weights of tags (by element, and by
whether they carry a class or id that names page furniture) and of words (by whether they are link text and by the
furniture they lie in) come from labelled pages. One linear scan finds the contiguous region of largest total, and its
text is the article. Comments, scripts, styles, forms, drawings, players, choices and furniture inside the region are left
out of it.

Labelled pages: pages whose author marked the article element. A bounded sample of them (`sample`, a documented
parameter) fits the weights; without any, the fixed starting weights hold.

Defined results: a null page is empty; a page without a region has an empty text; references are decoded, white
space inside a block is one space, blocks are joined by two line feeds; the tree may be unclosed or cut off; rows are
independent, so repeated rows give repeated results; an empty table gives no rows.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship

#: Element names by role.
BLOCK = frozenset("address article aside blockquote body br_ caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
#: Hold text only, up to their end tag; the first three reach to the page's end without one.
RAW = frozenset("script style textarea iframe xmp noembed noframes".split())
#: Ordinary nested elements whose contents are not page text.
MUTED = frozenset("noscript template svg math object select canvas audio video".split())
#: Elements that end an open svg or math element, whose end tag is missing.
BREAKS = frozenset("blockquote body br center dd div dl dt embed h1 h2 h3 h4 h5 h6 head hr img li main article section menu ol p pre table ul".split())
#: A page's layout with or without a piece of furniture, not the furniture.
LAYOUT = re.compile(r"(?:^|(?<=\s))(?:has|with|no|without)[_-]\S+", re.I)
FURNITURE = frozenset("nav header footer aside form button menu dialog label fieldset head title".split())
CLOSES_P = BLOCK - {"body", "html", "title"}
NAMES = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|cookie\w*|consent|notice|alert|popup|modal|newsletter|subscribe|sidebar|side|nav\w*|menu|breadcrumb\w*|footer|header|masthead|comments?|disqus|replies|respond|related|recommend\w*|share|social|widget|toolbar|pager|pagination|login|signup|search)(?:$|[\s_-])", re.I)
#: Words beside those of NAMES in class names that say nothing of their own. A name with any other word beside (related-work,
#: share-price) may be the article's own: such an element is kept where it holds prose.
PLAIN = frozenset("area articles article author bar bars bio block blocks body bottom box boxes btn button buttons card cards col column container content desktop entry ext floating footer form global grid group header heading hidden icons inner item items label left link links list main media message mobile module more msg news overlay outer page panel post posts primary rail read reading right row section secondary site sizes slot small space sticky stories story sub tag tags text title top topics unit wrap wrapper".split())
PROSE, LINKED = 40, 0.25
#: Inline elements that an unclosed paragraph's end closes with it, and elements of doubtful names that are open at once: inside
#: so many, further ones are furniture.
COVERS, DOUBTS = frozenset("b i em strong a span u font small".split()), 16
ROLES = frozenset("navigation banner contentinfo complementary search form menu alert dialog".split())
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)(?:>|$)|<[!?][^>]*(?:>|$)", re.S)
ATTR = re.compile(r"(class|id|role|hidden|aria-hidden)\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?", re.I)
START = {"word": 1.0, "link": -1.0, "furniture": -0.5, "tag": -2.0, "mark": -0.5, "hard": -6.0}
INLINE = frozenset("a abbr b bdi bdo big cite code del dfn em font i ins kbd mark q s samp small span strike strong sub sup time tt u var wbr br img".split())


def _odd(name: str, attrs: str, classes: bool = True) -> bool:
    """Whether an element is page furniture by its name, role or, with `classes`, its class or id."""
    if name in FURNITURE:
        return True
    for m in ATTR.finditer(attrs):
        k, v = m[1].lower(), (m[2] or "").strip("\"'")
        if k == "hidden" or (k == "aria-hidden" and v.lower() == "true") or (k == "role" and v.lower() in ROLES) or (classes and k in ("class", "id") and NAMES.search(LAYOUT.sub("", v))):
            return True
    return False


def _doubtful(attrs: str) -> bool:
    """Whether class and id name furniture only beside words of another meaning."""
    found = False
    for m in ATTR.finditer(attrs):
        if m[1].lower() in ("class", "id"):
            for name in (m[2] or "").strip("\"'").split():
                if NAMES.search(LAYOUT.sub("", name)):
                    words = [w for w in re.split(r"[_-]+|\d+", name.lower()) if w and not NAMES.search(w) and w not in PLAIN]
                    if not words or re.search(r"comment|repl(?:y|ies)|respond|disqus", name, re.I):
                        return False
                    found = True
    return found


def tokens(page: str):
    """(kind, value, furniture depth, inside the article element): kind is a feature name of START, value the tag or the text.

    Where all article elements lie in furniture, elements around the longest one are no furniture by class or id; nor
    are elements of a doubtful name that hold at least PROSE words, of which at most the share LINKED is link text."""
    out, articles, doubtful = _tokens(page, frozenset())
    free = {place for place, words, linked in doubtful if words >= PROSE and linked <= LINKED * words}
    if articles and all(odd for _, _, odd, _ in articles):
        free |= set(max(articles, key=lambda a: a[3])[1])
    if free:
        out, articles, _ = _tokens(page, frozenset(free))
    return out, bool(articles)


def _tokens(page: str, around: frozenset[int]):
    """Tokens; of each article element [place, places of the elements around it, furniture depth, words]; of each element that
    is furniture by a doubtful name only [place, words, words of links]. Elements whose places are in `around` are no
    furniture by class or id."""
    stack: list[tuple[str, bool, int]] = []
    #: How many elements of a name are open, and of each the place on the stack of a paragraph that only inline elements cover.
    opened: Counter[str] = Counter()
    reach: list[int] = []
    doubtful: list[list[int]] = []
    open_doubts: dict[int, list[int]] = {}
    odd = article = link = muted = 0
    at = 0
    out = []
    articles: list[list] = []
    open_articles: list[list] = []
    n = len(page)
    lower = page.lower() if len(page.lower()) == n else page
    last: dict[str, int] = {}

    def ends(name: str) -> bool:
        """Whether an end tag of that name is still to come."""
        if name not in last:
            last[name] = lower.rfind(f"</{name}")
        return last[name] >= at

    def pop() -> str:
        nonlocal odd, link, article, muted
        t, o, place = stack.pop()
        reach.pop()
        opened[t] -= 1
        open_doubts.pop(place, None)
        odd -= o
        link -= t == "a"
        muted -= t in MUTED
        if t == "article":
            article -= 1
            open_articles.pop()
        return t

    while at < n:
        m = TOKEN.search(page, at)
        stop = m.start() if m else n
        if stop > at and not muted:
            out.append(("furniture" if odd else "link" if link else "word", page[at:stop], odd, article > 0))
            if open_articles or open_doubts:
                many = len(page[at:stop].split())
                for a in open_articles:
                    a[3] += many
                for d in open_doubts.values():
                    d[1] += many
                    d[2] += many * (link > 0)
        if not m:
            break
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        closing = bool(m[1])
        alone = (m[3] or "").endswith("/")
        if not closing:
            if name in RAW:
                close = None if alone else re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at) if ends(name) else None
                if close:
                    at = close.end()
                elif not alone and name in ("script", "style", "textarea"):
                    at = n
                if not muted:
                    out.append(("tag", name, odd, article > 0))
                continue
            if muted and name in BREAKS:
                for t, _, _ in reversed(stack):
                    if t in ("svg", "math"):
                        while pop() != t:
                            pass
                        break
                    if t in MUTED or t == "foreignobject":
                        break
            if name in MUTED and (alone or not ends(name)):
                if not muted:
                    out.append(("tag", name, odd, article > 0))
                continue
            if not muted and name in CLOSES_P:
                if reach and reach[-1] >= 0:
                    while pop() != "p":
                        pass
            if not muted and name == "li" and stack and stack[-1][0] == "li":
                pop()
        weird = not closing and not muted and name not in ("body", "html", "article", "main", *MUTED) and _odd(name, m[3] or "", m.start() not in around) and not (name == "header" and article)
        inside, quiet = article > 0, muted > 0
        if closing:
            if opened[name]:
                while pop() != name:
                    pass
            inside = inside and article > 0
        elif name not in VOID and not alone:
            if name == "article":
                a = [m.start(), [p for _, _, p in stack], odd, 0]
                articles.append(a)
                open_articles.append(a)
            if weird and not _odd(name, m[3] or "", False) and len(open_doubts) < DOUBTS and _doubtful(m[3] or ""):
                open_doubts[m.start()] = [m.start(), 0, 0]
                doubtful.append(open_doubts[m.start()])
            reach.append(len(stack) if name == "p" else reach[-1] if reach and name in COVERS else -1)
            stack.append((name, weird, m.start()))
            opened[name] += 1
            odd += weird
            link += name == "a"
            article += name == "article"
            muted += name in MUTED
        if not (quiet and muted):
            out.append(("hard" if weird or (closing and name in FURNITURE) else "mark" if name in INLINE else "tag", name, odd, inside))
    return out, articles, doubtful


def _count(page: str) -> dict[str, list[int]] | None:
    """For a page with an article element: per feature, tokens inside and outside of it."""
    toks, labelled = tokens(page)
    if not labelled:
        return None
    c: dict[str, list[int]] = {}
    for kind, value, _, inside in toks:
        n = len(value.split()) if kind in ("word", "link", "furniture") else 1
        key = kind if kind in ("word", "link", "furniture", "hard") else f"tag:{value}"
        c.setdefault(key, [0, 0])[0 if inside else 1] += n
    return c


def fit_weights(pages: list[str]) -> dict[str, float]:
    """Weights from labelled pages: smoothed log odds of inside to outside, scaled to a word's, and held to their signs."""
    total: dict[str, list[float]] = {}
    for page in pages:
        for k, (a, b) in (_count(page) or {}).items():
            t = total.setdefault(k, [0.0, 0.0])
            t[0] += a
            t[1] += b
    w = dict(START)
    if not total:
        return w
    inside, outside = (sum(t[i] for t in total.values()) for i in (0, 1))
    odds = lambda k: math.log((total[k][0] + 1) / (inside + 1)) - math.log((total[k][1] + 1) / (outside + 1))
    for k in total:
        o = odds(k)
        if k == "word":
            w[k] = min(max(o, 0.5), 2.0)
        elif k == "link":
            w[k] = min(max(o, -2.0), 0.5)
        elif k == "furniture":
            w[k] = min(max(o, -1.0), -0.25)
        elif k == "hard":
            w[k] = min(max(2 * o, -8.0), -4.0)
        else:
            w[k] = min(max(o - 1, -6.0), -0.05)
    return w


def region(toks: list, w: dict[str, float]) -> tuple[int, int]:
    """The contiguous run of tokens of largest total; (0, 0) where none is positive. Earliest of equal ones."""
    best = run = 0.0
    lo = hi = start = 0
    for i, (kind, value, odd, inside) in enumerate(toks):
        if inside and (odd or kind == "hard"):  # furniture nested in an article element is left out, not a border
            continue
        if kind in ("word", "link", "furniture"):
            run += w[kind] * len(value.split())
        else:
            run += w["hard"] if kind == "hard" else w.get(f"tag:{value}", w[kind])
        if run <= 0:
            run, start = 0.0, i + 1
        elif run > best:
            best, lo, hi = run, start, i + 1
    return lo, hi


def main_text(page: str, w: dict[str, float]) -> str:
    toks, _ = tokens(page)
    lo, hi = region(toks, w)
    blocks, now = [], []

    def close():
        t = " ".join(entities.unescape("".join(now)).split())
        if t:
            blocks.append(t)
        now.clear()

    for kind, value, odd, _ in toks[lo:hi]:
        if kind in ("word", "link"):
            now.append(value)
        elif kind == "furniture":
            continue
        elif value in BLOCK:
            close()
        elif value == "br":
            now.append(" ")
    close()
    return "\n\n".join(blocks)


def _extractor(w: dict[str, float]):
    def run(batches):
        for batch in batches:
            texts = [main_text(p or "", w) for p in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return run


def extract(pages: DataFrame, sample: int = 200, weights: dict[str, float] | None = None) -> DataFrame:
    """page_id, url, text, n_chars. Weights are fitted on at most `sample` pages with an article element, drawn by hash."""
    ship(pages.sparkSession)
    if weights is None:
        marked = pages.filter(F.contains(F.lower("html"), F.lit("<article"))).select("page_id", "html")
        # each partition would send `sample` whole pages to the driver: the expected lowest hashes are kept before that
        share = min(1.0, 2 * sample / max(1, marked.count()))
        lowest = F.xxhash64("page_id") <= F.lit(int(share * (2**64 - 1)) - 2**63 if share < 1 else 2**63 - 1)
        seen = marked.filter(lowest).orderBy(F.xxhash64("page_id"), "page_id").limit(sample)
        weights = fit_weights([r["html"] for r in seen.collect()])
    return pages.select("page_id", "url", "html").mapInArrow(_extractor(weights), "page_id long, url string, text string, n_chars long")


def op8_html_extraction(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
