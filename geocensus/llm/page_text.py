"""Main text of HTML pages: containers are scored and lifted to the whole article, hosts vote on their generalised paths, and pages are
read again by the winner."""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocensus.llm.shared import materialise

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(?:noscript|template|textarea|svg|iframe|select|title|object|video|audio|canvas|script|style)\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*/>|<(script|style|noscript|template|textarea|svg|iframe|select|title|object|video|audio|canvas)\b[^>]*>.*?(?:</\1\s*>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|[^<]+|<", re.S | re.I)
_CLASS = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_BREAKS = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
_HOLDERS = frozenset("article aside blockquote body details dialog div dl fieldset figure footer form header html main menu nav ol section table tbody td tr ul".split())
_OUTSIDE = frozenset("nav header footer aside form menu dialog button head".split())
_NOISE = frozenset("ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments cookie consent disqus footer header masthead menu modal nav navbar navigation newsletter notice notices popup promo promoted promotion recommended related reply replies respond share sharing sidebar social sponsor sponsored subscribe toolbar widget".split())
_SPACE = re.compile(r"\s+")
_TAIL = re.compile(r"\d+")
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_TALK = re.compile(r"comment|disqus|repl(?:y|ies)|respond", re.I)
_UNSAID = frozenset("has with no without hide show is".split())
_STEP = re.compile(r"(?:^|>)(?:article|main)(?=[.>]|$)")
#: A sum of gains from which blocks outside a container are taken for text of the page: one block of full weight.
REAL = 40


def _names_noise(tag: str, value: str) -> bool:
    """Whether a class or id names no part of an article; ``has-sidebar`` and its like tell of the layout only."""
    for k, name in enumerate(value.split()):
        words = re.findall(r"[a-z]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", name).lower())
        if tag == "main" or tag == "article" and k:
            break
        if any(w in _NOISE for w in (words[:1] if tag == "article" else words)) and not (words and words[0] in _UNSAID):
            return True
    return False


def _label(tag: str, attrs: str, inside: bool = False) -> tuple[str, bool, bool]:
    """A container's step of the path, digits generalised; whether it is no part of an article; and whether only its names say so.

    ``inside`` an article, a header is the article's own.
    """
    names: list[str] = []
    hard, named = tag in _OUTSIDE and not (tag == "header" and inside), False
    for kind, a, b, c in _CLASS.findall(attrs):
        value = (a or b or c).strip()
        if kind.lower() == "role":
            hard = hard or value.lower() in {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alert"}
        elif not (inside and re.search(r"header\b|masthead|banner", value.lower()) and not _names_noise(tag, re.sub(r"(?i)header|masthead|banner", "", value))):
            named = named or _names_noise(tag, value)
        if kind.lower() == "class":
            names += sorted(set(_TAIL.sub("N", value).split()))
    page = tag in {"html", "body"}
    return ".".join([tag, *names]), hard and not page, named and not page


def blocks(page: str) -> list[tuple[str, str, int, bool]]:
    """The page's text blocks in order: path of the nearest container, text, characters in links, whether it is noise.

    Names alone do not make noise of a container that holds an article or, on pages without one, most of the text.
    """
    return [b[:4] for b in _blocks(page)]


def _blocks(page: str) -> list[tuple[str, str, int, bool, str]]:
    """``blocks`` with the tag of the heading that each is, if any."""
    out: list[tuple[str, str, int, bool, str, tuple[int, ...]]] = []
    stack: list[tuple[str, str, bool, tuple[int, ...]]] = []  # tag, path, noise, numbers of the containers whose names say noise
    talk: list[bool] = []  # of those: whether it holds comments
    cleared: set[int] = set()
    held: list[str] = []
    links = inside = 0
    heading = ""

    def flush() -> None:
        nonlocal held, links
        if held:
            text = _SPACE.sub(" ", entities.unescape("".join(held))).strip()
            if text:
                top = stack[-1] if stack else ("", "", False, ())
                out.append((top[1], text, links, top[2], heading, top[3]))
        held, links = [], 0

    for m in _TOKEN.finditer(page):
        tag = m[3]
        if tag is None:
            token = m[0]
            if token[0] != "<" or token == "<":
                held.append(token)
                if inside:
                    links += len(token)
            continue
        tag, closing, ended = tag.lower(), bool(m[2]), m[4].endswith("/")
        if tag == "a":
            inside = 0 if closing or ended else 1
        elif tag == "br" or tag == "img":
            held.append(" ")
        if tag not in _BREAKS and tag not in _OUTSIDE:
            continue
        flush()
        heading = tag if tag in _HEADINGS and not closing else ""
        if tag in _HOLDERS or tag in _OUTSIDE:
            if closing:
                at = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), None)
                if at is not None:
                    del stack[at:]
            elif not ended:
                up = stack[-1] if stack else ("", "", False, ())
                step, noise, named = _label(tag, m[4], bool(_STEP.search(up[1])))
                over = up[3]
                if named:
                    over = (*over, len(talk))
                    talk.append(bool(_TALK.search(m[4])))
                elif not noise and tag in ("article", "main"):
                    cleared.update(n for n in over if not talk[n])
                stack.append((tag, f"{up[1]}>{step}" if up[1] else step, noise or up[2], over))
            inside = 0
    flush()
    if talk and not any(_STEP.search(path) for path, _, _, noise, _, over in out if not noise and cleared.issuperset(over)):
        held_by, whole = [0.0] * len(talk), 0.0
        for _, text, n, noise, _, over in out:
            if not noise:
                whole += _gain(text, n)
                for k in over:
                    held_by[k] += _gain(text, n)
        cleared.update(k for k, g in enumerate(held_by) if not talk[k] and 2 * g > whole)
    return [(path, text, n, noise or any(k not in cleared for k in over), h) for path, text, n, noise, h, over in out]


def _gain(text: str, links: int) -> float:
    """A block's text outside links; short blocks count for less."""
    return max(0, len(text) - 2 * links) * min(1.0, len(text) / 40)


def _below(path: str, top: str) -> bool:
    return path == top or path.startswith(top + ">") or not top


def container_scores(found: list[tuple]) -> dict[str, float]:
    """Per container path: its own text outside links, plus half of what its child containers hold, long blocks most."""
    own: dict[str, float] = {}
    for path, text, links, noise, *_ in found:
        if not noise and path:
            own[path] = own.get(path, 0.0) + _gain(text, links)
    total: dict[str, float] = {}
    for path, gain in own.items():
        while path:
            total[path] = total.get(path, 0.0) + gain
            path, gain = path.rpartition(">")[0], gain * 0.5
    return total


def lifted(found: list[tuple], path: str) -> str:
    """The container whose blocks are the text: the outermost article or main around ``path``; without one, the highest ancestor
    that adds blocks outside links, or a heading before the text, to what the container below it holds."""
    ends = [m.start() + len(m[0]) for m in _STEP.finditer(path)]
    if ends:
        at = path.find(">", ends[0])
        return path if at < 0 else path[:at]
    top, up = path, path
    while ">" in up:
        up = up.rpartition(">")[0]
        added = 0.0
        before = True
        for p, text, links, noise, *h in found:
            if noise or not _below(p, up):
                continue
            if _below(p, top):
                before = False
            elif 2 * links < len(text):
                added += REAL if h and h[0] and (before or h[0] == "h1") else _gain(text, links)
        if added >= REAL:
            top = up
    return top


def best_path(found: list[tuple]) -> tuple[str, float]:
    scores = container_scores(found)
    if not scores:
        return "", 0.0
    path, score = min(scores.items(), key=lambda x: (-x[1], -len(x[0]), x[0]))
    return lifted(found, path), score


def read(found: list[tuple], path: str | None) -> str:
    """The blocks below ``path``, lifted as this page needs, or below the page's own best container where it has no such path."""
    if not path or not any(not b[3] and _below(b[0], path) for b in found):
        path = best_path(found)[0]
    else:
        path = lifted(found, path)
    return "\n".join(b[1] for b in found if not b[3] and _below(b[0], path))


def host_of(url_col: str) -> Column:
    return F.coalesce(F.lower(F.regexp_extract(url_col, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def vote(pages: DataFrame, url_col: str = "url", html_col: str = "html", share: float = 0.5) -> DataFrame:
    """``host, path``: the path that most of a host's pages score best, if it has ``share`` of the votes."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            best = [best_path(_blocks(h)) for h in b["html"]]
            out = pd.DataFrame({"host": b["host"], "path": [p for p, _ in best], "votes": [1 if p else 0 for p, _ in best], "score": [s for _, s in best]})
            yield out.groupby(["host", "path"], as_index=False).agg({"votes": "sum", "score": "sum"})

    ballots = pages.select(host_of(url_col).alias("host"), F.coalesce(F.col(html_col), F.lit("")).alias("html")).mapInPandas(run, "host string, path string, votes long, score double")
    ballots = materialise(ballots.where("path <> ''").groupBy("host", "path").agg(F.sum("votes").alias("votes")), "page-votes")
    won = ballots.groupBy("host").agg(F.sum("votes").alias("all"), F.max(F.struct("votes", F.negative(F.length("path")).alias("short"), "path")).alias("w"))
    return won.where(F.col("w.votes") >= share * F.col("all")).select("host", F.col("w.path").alias("path"))


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, text``: one row per page.

    Null or empty html, and pages without a container that has text of its own, give an empty text; pages without a usable
    host vote together; rows that repeat an id are read each on its own; an empty table gives no rows.  Blocks are joined by one
    newline, white space inside them is one blank, character references are decoded; nothing else is dropped or capped.
    Only host, path and vote counts are shuffled, already summed per batch; if the winners are few they are broadcast to the
    pages, else both meet by host, where Spark may split a hot host.
    """
    from geocensus.llm.shared import join_checked

    winners = materialise(vote(pages, url_col, html_col), "page-winners")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"page_id": b["page_id"], "url": b["url"], "text": [read(_blocks(h), p) for h, p in zip(b["html"], b["path"], strict=True)]})

    d = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"), host_of(url_col).alias("host"))
    d = join_checked(d, winners, "host", rows=20_000).select("page_id", "url", "html", "path")
    return d.mapInPandas(run, f"page_id {d.schema['page_id'].dataType.simpleString()}, url string, text string")
