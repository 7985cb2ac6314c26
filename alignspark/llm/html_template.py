"""Main text of web pages, by template deduction over the pages of a host.

A page is read as a series of tags and texts. Each block element, named by its path of open block elements, is a template
token, and so is each block of text with its path; its occurrence vector is the number of times it stands on each page of the host. Tokens of one host with equal
vectors form an equivalence class (vectors are compared by a sum of hashed page terms, so they are gathered by a plain
grouped sum, however many pages a host has). A class is valid if its tokens stand on enough of the pages; valid classes
nest by their paths into the host's template. What lies under menus, headers, footers, asides, notices, adverts, forms
and comments is not main text; of the rest the article is the innermost element of the class found once a page that keeps
most of the text which stands outside links. Text of a valid class is template, too: on each page the slots between are
what the smallest container of all other text holds (the whole article or main element, where there is one), and template
text outside it or in a container that holds nothing else is left out. Template text among an article's own stays, as does
all text of a page that has none of its own. Words inside a block are no tokens of their own. Pages of a host without a valid class fall
back on the class found over all hosts, then on their own elements.

Edge cases: null and empty html give an empty text; unclosed tags, comments and scripts end where the page ends;
self-closed or unclosed svg, button, select, iframe, noscript and template end at their tag; a null
url counts as a host of its own; repeated rows are pages of their own; pages are read whole; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter, defaultdict
from collections.abc import Collection, Iterable, Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, tidy
from .url_filter import split_url

TOKEN = re.compile(
    r"""<!--.*?(?:-->|\Z)|<(script|style|textarea)\b(?:.*?</\1\s*>|.*\Z)|<(noscript|template|svg|iframe|select|button)\b(?>(?:[^>"']|"[^"]*"|'[^']*')*)(?<!/)>(?:(?!<\2\b).)*?</\2\s*>|<[a-zA-Z/!?](?>(?:[^>"']|"[^"]*"|'[^']*')*)>|<[a-zA-Z/!?][^>]*>|[^<]+|<""",
    re.S | re.I,
)
NAME = re.compile(r"</?\s*([a-zA-Z][a-zA-Z0-9:-]*)")
ATTRIBUTE = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
#: Block elements, those without an end tag, those that close an open paragraph's kind.
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
ALONE = frozenset("hr".split())
CLOSED_BY_ITSELF = frozenset("p li dt dd td th tr option".split())
#: Elements and whole class, id and role names that mark what isn't main text.
BESIDES = frozenset("nav menu aside footer form head title dialog dir fieldset".split())
MARKS = frozenset("ad ads advert advertisement adverts banner breadcrumb breadcrumbs comment comments cookie cookies consent footer form header menu modal nav navbar navigation newsletter notice notices pager pagination popup promo promoted related replies search share sharing sidebar social sponsor sponsored subscribe toolbar widget".split())
MAIN = frozenset("article main".split())
#: Elements that no name marks.
UNMARKED = MAIN | {"html", "body"}
LEAST_SHARE, KEEPS = 0.5, 0.8
#: Pages on which template text stands at least; blocks that are parts of a text, not containers of texts.
LEAST_PAGES = 3
PARTS = frozenset("address blockquote caption dd dt figcaption h1 h2 h3 h4 h5 h6 hgroup legend li option p pre summary".split())


def _marks(tag: str) -> set[str]:
    names = " ".join("".join(x) for x in ATTRIBUTE.findall(tag)).lower().rstrip("/")
    return set(names.split()) & MARKS


def read_page(page: str | None, spare: tuple[str, ...] | None = ()) -> Iterator[tuple[tuple[str, ...], bool, bool, str, tuple[int, ...]]]:
    """(path of open block elements, beside the main text?, inside a link?, text, numbers of the path's elements on the page)
    for each text; text "" for an element's start.

    Elements of the path carry their names' marks, so that a div of adverts is another token than a plain div. Names
    never put article, main, body or an element of the path spare beside the main text; None spares all.
    """
    path: list[tuple[str, bool, int]] = []
    besides = links = number = 0
    for m in TOKEN.finditer(page or ""):
        token = m[0]
        if token[0] != "<" or len(token) == 1:
            yield tuple(x for x, _, _ in path), besides > 0, links > 0, entities.unescape(token), tuple(n for _, _, n in path)
            continue
        if m[1] or m[2] or token[1] in "!?":
            continue
        name = NAME.match(token)
        tag = name[1].lower() if name else ""
        if tag == "a":
            links = 0 if token[1] == "/" else 1
        elif tag == "br":
            yield tuple(x for x, _, _ in path), besides > 0, links > 0, " ", tuple(n for _, _, n in path)
        if tag not in BLOCKS:
            continue
        if token[1] == "/":
            at = next((i for i in range(len(path) - 1, -1, -1) if path[i][0].split(".")[0] == tag), None)
            if at is not None:
                besides -= sum(b for _, b, _ in path[at:])
                del path[at:]
                yield tuple(x for x, _, _ in path), besides > 0, False, "", ()
            continue
        if path and path[-1][0].split(".")[0] == "p" or path and path[-1][0].split(".")[0] == tag and tag in CLOSED_BY_ITSELF:
            besides -= path.pop()[1]
        marks = _marks(token) if "=" in token and tag not in UNMARKED else set()
        inside = any(x.split(".")[0] in MAIN for x, _, _ in path)
        named = ".".join([tag, *sorted(marks)])
        spared = not marks or spare is None or len(path) < len(spare) and (*(x for x, _, _ in path), named) == spare[: len(path) + 1]
        beside = tag in BESIDES or not spared or tag == "header" and not inside
        if tag not in ALONE and not token.endswith("/>"):
            number += 1
            path.append((named, beside, number))
            besides += beside
        links = 0
        yield tuple(x for x, _, _ in path), besides > 0, False, "", ()


def text_token(path: tuple[str, ...], line: str) -> int:
    """Number of a block of text at its place."""
    return xxhash.xxh64_intdigest("/".join(path) + "\t" + line) - (1 << 63)


def text_blocks(found: Iterable[tuple]) -> Iterator[tuple[tuple[str, ...], bool, str, tuple[int, ...]]]:
    """(path, beside the main text?, text, numbers of the path's elements) of each block with text."""
    now, at = [], ((), False, ())
    for path, beside, _, text, numbers in [*found, ((), False, False, "", ())]:
        if text:
            now.append(text)
            at = path, beside, numbers
            continue
        if line := " ".join("".join(now).split()):
            yield at[0], at[1], line, at[2]
        now = []


def tokens_of(page: str | None) -> tuple[Counter, Counter]:
    """(starts of each template token, characters outside links and besides under each)."""
    starts, chars = Counter(), Counter()
    last: tuple[str, ...] = ()
    for path, beside, link, text, _ in read_page(page):
        if not text:
            if len(path) > len(last) or path and path[:-1] == last[: len(path) - 1] and len(path) == len(last):
                starts[path] += 1
        elif not beside and not link and not text.isspace():
            for k in range(1, len(path) + 1):
                chars[path[:k]] += len(text)
        last = path
    return starts, chars


def texts_of(page: str | None) -> Counter:
    """Each text token that isn't beside, as a tab and its number: no element's path has a tab."""
    return Counter(f"\t{text_token(path, line)}" for path, beside, line, _ in text_blocks(read_page(page)) if not beside)


STATS = "host string, token string, vector long, pages long, times long, chars long, once long"


def template_tokens(pages: DataFrame) -> DataFrame:
    """host, token, vector, pages, times, chars, once: summed over the host's pages. once: pages on which it stands once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums: dict[tuple[str, str], list[int]] = defaultdict(lambda: [0] * 5)
            for host, term, page in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                starts, chars = tokens_of(page)
                starts[()] = 1
                counted = [("/".join(token), n, chars[token]) for token, n in starts.items()]
                for token, n, size in [*counted, *((token, n, 0) for token, n in texts_of(page).items())]:
                    s = sums[host, token]
                    for k, v in enumerate((term * n, 1, n, size, n == 1)):
                        s[k] += v
            rows = [(*k, (v[0] + (1 << 63)) % (1 << 64) - (1 << 63), *v[1:]) for k, v in sums.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string() if i < 2 else pa.int64()) for i in range(7)], names=["host", "token", "vector", "pages", "times", "chars", "once"])

    rows = pages.select(_host().alias("host"), F.xxhash64("page_id", "url").alias("term"), F.col("html").cast("string"))
    found = rows.mapInArrow(tidy(run), STATS).groupBy("host", "token")
    # sums of hashes may wrap: they are taken in halves; text of fewer pages is no template's
    summed = found.agg(((F.sum(F.col("vector").bitwiseAND(F.lit(0xFFFFFFFF))) + F.sum(F.shiftright("vector", 32)) * F.lit(1 << 20)) % F.lit((1 << 61) - 1)).alias("vector"), *[F.sum(c).alias(c) for c in ("pages", "times", "chars", "once")])
    return summed.where(~F.col("token").startswith("\t") | (F.col("pages") >= LEAST_PAGES))


def _host():
    return F.coalesce(split_url(F.col("url"))[0], F.lit(""))


def article_path(tokens: list[dict]) -> str | None:
    """Path of the article among one host's template tokens, or None if no class is valid."""
    pages = next((t["pages"] for t in tokens if t["token"] == ""), 0)
    classes: dict[int, list[dict]] = defaultdict(list)
    for t in tokens:
        if t["token"] and t["token"][0] != "\t":
            classes[t["vector"]].append(t)
    skeleton = [t for members in classes.values() if len(members) > 1 for t in members if t["pages"] >= LEAST_SHARE * pages and t["once"] == t["pages"] and t["chars"]]
    if not skeleton:
        return None
    named = [t for t in skeleton if t["token"].split("/")[-1].split(".")[0] in MAIN]
    if named:
        return max(named, key=lambda t: (t["chars"], -len(t["token"]), t["token"]))["token"]
    most = max(t["chars"] for t in skeleton)
    return max((t for t in skeleton if t["chars"] >= KEEPS * most), key=lambda t: (t["token"].count("/"), t["chars"], t["token"]))["token"]


def template_texts(tokens: list[dict]) -> list[int]:
    """Text tokens of valid classes: those on every page, and those with the occurrence vector of a frequent element."""
    pages = next((t["pages"] for t in tokens if t["token"] == ""), 0)
    elements = {t["vector"] for t in tokens if t["token"][:1] != "\t" and t["pages"] >= LEAST_SHARE * pages}
    return sorted(int(t["token"]) for t in tokens if t["token"][:1] == "\t" and t["pages"] >= LEAST_PAGES and (t["pages"] == pages or t["vector"] in elements))


def templates(tokens: DataFrame, most_tokens: int = 2000) -> DataFrame:
    """host, article, texts: a row for each host with a valid template. Tokens on few pages can't be in a valid class and stay behind."""
    of = tokens.where("token = ''").select(F.col("host").alias("of"), F.col("pages").alias("all"))
    often = tokens.join(of, F.col("host") == F.col("of")).where(F.col("pages") >= LEAST_SHARE * F.col("all")).drop("of", "all")

    def pick(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        return pa.table({"host": pa.array([rows[0]["host"]], pa.string()), "article": pa.array([article_path(rows)], pa.string()), "texts": pa.array([template_texts(rows)], pa.list_(pa.int64()))})

    return often.groupBy("host").applyInArrow(pick, "host string, article string, texts array<long>").where("article IS NOT NULL OR size(texts) > 0")


def main_text(page: str | None, article: str | None, texts: Collection[int] = ()) -> str:
    """Text of the article's blocks without the template's texts, one a line; names that would hide the article or the whole page mark nothing."""
    goal = tuple(article.split("/")) if article else ()
    found = list(read_page(page, goal))
    own = sorted({p[: i + 1] for p, _, _, text, _ in found if text and not text.isspace() for i, x in enumerate(p) if x.split(".")[0] in MAIN}, key=len)
    blocks = _blocks(found, goal, texts)
    if own and not any(p[: len(g)] == g and not beside for p, beside, _, text, _ in found if text and not text.isspace() for g in own):
        # one article that is all hidden, and longer than what is seen, is the page's; several are comments and the like
        once = [g for g in own if tokens_of(page)[0][g] == 1]
        hidden = _blocks(list(read_page(page, once[0])), once[0], texts) if once else []
        blocks = max(blocks, hidden, key=lambda x: sum(map(len, x)))
    return "\n".join(blocks or _blocks(list(read_page(page, None)), goal, texts))


def _blocks(found: list, goal: tuple[str, ...], texts: Collection[int]) -> list[str]:
    paths = {p for p, _, _, text, _ in found if text}
    if not goal or not any(p[: len(goal)] == goal for p in paths):
        own = sorted({p[: i + 1] for p in paths for i, x in enumerate(p) if x.split(".")[0] in MAIN}, key=len)
        goal = own[0] if own else next(((x,) for x in ("html", "body") if any(p[:1] == (x,) for p in paths)), ())
        if goal == ("html",) and any(p[:2] == ("html", "body") for p in paths):
            goal = ("html", "body")
    blocks = [(p, line, n) for p, beside, line, n in text_blocks(found) if not beside and p[: len(goal)] == goal]
    own = [not texts or text_token(p, line) not in texts for p, line, _ in blocks]
    if any(own) and not all(own):
        blocks = _slots(blocks, own)
    return [line for _, line, _ in blocks]


def _slots(blocks: list[tuple[tuple[str, ...], str, tuple[int, ...]]], own: list[bool]) -> list[tuple[tuple[str, ...], str, tuple[int, ...]]]:
    """Blocks that are a page's own, and template text among them."""

    def container(path: tuple[str, ...], depth: int) -> int:
        while depth and path[depth - 1].split(".")[0] in PARTS:
            depth -= 1
        return depth

    mine = [(p, n) for (p, _, n), o in zip(blocks, own) if o]
    path, numbers = mine[0]
    depth = min(next((i for i, (a, b) in enumerate(zip(numbers, n)) if a != b), min(len(numbers), len(n))) for _, n in mine)
    depth = container(path, depth)
    depth = next((i + 1 for i in range(depth - 1, -1, -1) if path[i].split(".")[0] in MAIN), depth)
    filled = {n[:i] for _, n in mine for i in range(len(n) + 1)}
    return [b for b, o in zip(blocks, own) if o or b[2][:depth] == numbers[:depth] and b[2][: container(b[0], len(b[0]))] in filled]


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of each row of pages."""
    stats = cut(template_tokens(pages), "tokens")
    by_host = cut(templates(stats), "templates")
    everywhere = stats.where(~F.col("token").startswith("\t")).groupBy("token").agg(F.lit("").alias("host"), F.sum(F.col("vector") % (1 << 40)).alias("vector"), *[F.sum(c).alias(c) for c in ("pages", "times", "chars", "once")])
    common = templates(everywhere.select("host", "token", "vector", "pages", "times", "chars", "once")).select("article").take(1)
    fallback = common[0]["article"] if common else None
    rows = pages.select("page_id", "url", F.col("html").cast("string").alias("html"), _host().alias("host"))
    rows = rows.join(by_host.withColumnRenamed("host", "of"), F.col("host") == F.col("of"), "left").select("page_id", "url", "html", F.coalesce("article", F.lit(fallback)).alias("article"), "texts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = [main_text(h, a, frozenset(t or ())) for h, a, t in zip(*(batch.column(k).to_pylist() for k in (2, 3, 4)), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(text, pa.string()), pa.array(map(len, text), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(tidy(run), "page_id long, url string, text string, n_chars long")
