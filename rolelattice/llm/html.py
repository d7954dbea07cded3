"""Main text of web pages by consensus of a host's pages on the path of the container that holds it."""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, table

# Element names by their role on a page.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe textarea title svg math object select option button canvas audio video".split())
DROP = frozenset("nav header footer aside menu dialog head label fieldset legend".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
LEAF = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd td th pre caption figcaption summary".split())
# An opening tag of the first ends an open element of the second within the third.
CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"tr"}), "th": ({"td", "th"}, {"tr"})}
NOISE = frozenset("ad ads adv advert adverts advertisement advertising sponsor sponsored sponsors promo promotion banner cookie cookies consent gdpr notice notices alert comment comments commentlist reply replies respond disqus sidebar aside menu nav navbar navigation breadcrumb breadcrumbs share sharing social related recommended newsletter subscribe subscription signup login popup modal overlay footer header masthead toolbar pagination pager widget hidden skip".split())
#: Of these, names of an article's own head, and of readers' comments.
HEADS, TALK = frozenset(("header", "masthead")), frozenset("comment comments commentlist reply replies respond disqus".split())
ROLES = frozenset("navigation banner contentinfo complementary search menu menubar dialog alert alertdialog form".split())

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']|\"[^\"]*+\"|'[^']*+')*+)(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)(?:>|\Z)", re.S)
ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
SPACE = re.compile(r"\s+")
ENDS = {t: re.compile(rf"</{t}(?=[\s/>]|\Z)", re.I) for t in RAW}
#: Path of a page without elements that hold others.
ROOT = "page"
ARTICLE = re.compile(r">(?:article|main)(?=[.>]|\Z)")


def names_noise(token: str) -> bool:
    """Whether a class or id as a whole says noise: each of its words does."""
    words = [w for w in re.split(r"[^a-z]+", token) if w]
    return bool(words) and NOISE.issuperset(words)


def label(tag: str, attrs: str) -> tuple[str, set[str], bool]:
    """The generalised name of an element (digits of its classes masked), the words of its classes and ids that say noise, and whether other attributes do."""
    if not attrs or "=" not in attrs and "hidden" not in attrs:
        return tag, set(), False
    got = {k.lower(): a or b or c for k, a, b, c in ATTR.findall(attrs)}
    classes = entities.unescape(got.get("class", "")).lower().split()
    named = {w for t in [*classes, *got.get("id", "").lower().split()] if names_noise(t) for w in re.split(r"[^a-z]+", t) if w}
    noise = got.get("role", "").lower() in ROLES or "hidden" in got or got.get("aria-hidden") == "true" or bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", got.get("style", ""), re.I))
    return ".".join([tag, *sorted({re.sub(r"\d+", "#", c) for c in classes})]), named, noise


@dataclass
class Named:
    """The elements of a page that are noise by name, numbered from 0: the characters outside links in them, and in articles in them."""

    held: list[list[int]] = field(default_factory=list)
    total: list[int] = field(default_factory=lambda: [0, 0])
    free: int = 0
    around: set[int] = field(default_factory=set)
    talk: set[int] = field(default_factory=set)

    def wraps(self) -> set[int]:
        """Those whose name does not count: they hold most of the text (of articles, if there are any), or articles that are nowhere else. Readers' comments are none of these."""
        k = int(self.total[1] > 0)
        most = {e for e, n in enumerate(self.held) if 2 * n[k] > self.total[k]}
        return (most if self.free else most | self.around) - self.talk


def blocks(page: str) -> list[tuple[str, str, int]]:
    """(path of the container, text, characters of links) of each block that is not noise, in page order; if names leave nothing, no name counts."""
    found, named = parse(page, set())
    if named.held:
        wraps = named.wraps()
        if wraps:
            found, _ = parse(page, wraps)
        if not found:
            found, _ = parse(page, set(range(len(named.held))))
    return found


def parse(page: str, lifted: set[int]) -> tuple[list[tuple[str, str, int]], Named]:
    """The blocks outside noise, where the names of lifted elements do not count, and what the named elements hold."""
    out: list[tuple[str, str, int]] = []
    stack: list[tuple[str, str, bool, tuple[int, ...], bool]] = []  # element, path, noise here or above, named elements here and above, noise for other reasons
    named = Named()
    words: list[str] = []
    state = {"links": 0}

    def flush() -> None:
        if words:
            # references are decoded before white space is folded
            t = SPACE.sub(" ", "".join(words)).strip()
            words.clear()
            if t:
                k = len(stack) - 1
                while k > 0 and (stack[k][0] in LEAF or stack[k][0] not in BLOCK):
                    k -= 1
                out.append((stack[k][1] if stack else ROOT, t, state["links"]))
        state["links"] = 0

    def close(k: int) -> None:
        if any(e[0] in BLOCK for e in stack[k:]):
            flush()
        del stack[k:]

    at, n = 0, len(page)
    noise, link = False, 0

    def take(s: str) -> None:
        if s and not link and not (stack and stack[-1][4]):
            size, inside = len(s.strip()), bool(stack) and in_article(stack[-1][1])
            named.total[0] += size
            named.total[1] += size * inside
            for e in stack[-1][3] if stack else ():
                named.held[e][0] += size
                named.held[e][1] += size * inside
            if inside and not stack[-1][3]:
                named.free += size
        if s and not noise:
            t = entities.unescape(s) if "&" in s else s
            words.append(t)
            if link:
                state["links"] += len(t)

    while at < n:
        m = TAG.search(page, at)
        if not m:
            rest = page[at:]
            take(rest)
            break
        take(page[at : m.start()])
        at = m.end()
        shut, tag, attrs = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
        if not tag:
            continue
        tag = tag.lower()
        if shut:
            k = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), -1)
            if k >= 0 and not (tag not in BLOCK and any(e[0] in BLOCK for e in stack[k + 1 :])):
                close(k)
            noise = bool(stack) and stack[-1][2]
            link = sum(e[0] == "a" for e in stack)
            continue
        if tag in RAW:
            end = ENDS[tag].search(page, at) if not attrs.rstrip().endswith("/") else None
            if end:
                close_at = page.find(">", end.end())
                at = n if close_at < 0 else close_at + 1
            elif not attrs.rstrip().endswith("/") and tag in ("script", "style", "textarea", "title"):
                at = n
            if not noise:
                words.append(" ")
            continue
        if tag in VOID:
            if tag == "hr":
                flush()
            elif tag == "br" and not noise:
                words.append(" ")
            continue
        if tag in BLOCK:
            flush()
            k = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == "p" or stack[i][0] in BLOCK), -1)
            if k >= 0 and stack[k][0] == "p":
                del stack[k:]
        if tag in CLOSES:
            ends, within = CLOSES[tag]
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in within:
                    break
                if stack[i][0] in ends:
                    close(i)
                    break
        name, says, bad = label(tag, attrs)
        above = stack[-1] if stack else ("", ROOT, False, (), False)
        path = f"{above[1]}>{name}" if tag in BLOCK and tag not in LEAF else above[1]
        heads, whole, mine = in_article(above[1]), tag in ("html", "body"), above[3]
        other = above[4] or bad and not whole or tag in DROP and not (tag == "header" and heads)
        if not whole and (says - HEADS if heads else says) or tag == "form":
            mine = (*mine, len(named.held))
            if says & TALK:
                named.talk.add(len(named.held))
            named.held.append([0, 0])
        if tag in ("article", "main") and not other:
            named.around.update(mine)
        stack.append((tag, path, other or not lifted.issuperset(mine), mine, other))
        noise = stack[-1][2]
        link += tag == "a"
    flush()
    return out, named


def in_article(path: str) -> bool:
    return bool(ARTICLE.search(path))


def top(path: str) -> str:
    """The outermost article or main on the path, else the path."""
    m = ARTICLE.search(path)
    return path if not m else path[: m.end()] + path[m.end() :].partition(">")[0]


def own_text(found: list[tuple[str, str, int]]) -> list[tuple[str, int]]:
    """(path, characters) of the blocks that say more outside links than in them: of those in articles, if these say most of the page."""
    said = [(p, len(t) - 2 * links) for p, t, links in found if len(t) > 2 * links]
    marked = [x for x in said if in_article(x[0])]
    return marked if 2 * sum(n for _, n in marked) >= sum(n for _, n in said) else said


def candidate(found: list[tuple[str, str, int]]) -> tuple[str, float]:
    """The container of the page's text and the text's characters outside links: the article or main with most of it, else the deepest element that holds all of it."""
    said = own_text(found)
    if not said:
        return "", 0.0
    if all(in_article(p) for p, _ in said):
        score: dict[str, float] = {}
        for p, n in said:
            score[top(p)] = score.get(top(p), 0.0) + n
        best = max(score, key=lambda p: (score[p], p))
        return best, score[best]
    steps = [p.split(">") for p, _ in said]
    low, high = min(steps), max(steps)
    k = next((i for i, (x, y) in enumerate(zip(low, high, strict=False)) if x != y), min(len(low), len(high)))
    return ">".join(low[:k]), float(sum(n for _, n in said))


def below(path: str, top: str) -> bool:
    return path == top or path.startswith(top + ">")


def host_of(url: F.Column) -> F.Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


def votes(pages: DataFrame) -> DataFrame:
    """host, path: for each host the path with the highest sum of scores (ties: more pages, then by name)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [candidate(blocks(p or "")) for p in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], ["host", "path", "score"])

    cast = pages.select(host_of(F.col("url")).alias("host"), "html").mapInArrow(run, "host string, path string, score double")
    tally = cast.where("path <> ''").groupBy("host", "path").agg(F.sum("score").alias("s"), F.count("*").alias("n"))
    first = F.row_number().over(Window.partitionBy("host").orderBy(F.desc("s"), F.desc("n"), "path"))
    return tally.withColumn("_r", first).where("_r = 1").select("host", "path")


def main_text(page: str, path: str | None) -> str:
    """All blocks in articles; unless these say most of the page, also those under the page's own container and under the host's path.

    A page of links alone without an article has the blocks under the host's path, or else all its blocks."""
    found = blocks(page)
    own, _ = candidate(found)
    held = [path] if path and (not own or not in_article(own)) else []
    held += [own] if own else []
    inside = [t for p, t, _ in found if in_article(p) or any(below(p, h) for h in held)]
    return "\n\n".join(inside or [t for _, t, _ in found])


#: Hosts whose paths are broadcast; beyond, pages are joined with them by salted host.
BROADCAST_HOSTS, SALTS = 100_000, 32


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars."""
    won = cut(votes(pages))
    keyed = pages.select("page_id", "url", "html", host_of(F.col("url")).alias("host"))
    if won.count() <= BROADCAST_HOSTS:
        joined = keyed.join(F.broadcast(won), "host", "left")
    else:
        salt = F.pmod(F.xxhash64("url", "page_id"), F.lit(SALTS)).cast("int")
        spread = won.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = keyed.withColumn("_s", salt).join(spread, ["host", "_s"], "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [main_text(p or "", w) for p, w in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(got, pa.string()), pa.array([len(t) for t in got], pa.int64())], ["page_id", "url", "text", "n_chars"])

    chosen = joined.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", "path")
    return chosen.mapInArrow(run, "page_id bigint, url string, text string, n_chars bigint")


def op8_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null and empty pages have an empty text; pages without a usable address share one host; repeated rows are extracted alike."""
    return extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
