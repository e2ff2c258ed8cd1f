"""Operator 8, HTML extraction with a suffix array for each host.

Pages become blocks of text, each with a role from the markup around it: article, main (inside a main element only), away
(what the markup plainly says is a menu, header, footer, sidebar, notice, advert, form or comment) or plain.  An article
inside a form or an element named as a sidebar or the like, which may wrap a whole page, counts if the page has no other.  Inside an
article only elements that can be nothing else go: nav, aside, form and so on, and class names that are exactly those of
adverts or comments, never parts of names.

What is not away is the page's token stream.  The streams of a host's pages are concatenated, and a suffix array finds the
runs of RUN_TOKENS tokens and the distinct pages that each stands on.  Blocks that repeated runs cover are boilerplate:

* on a page without an article, runs on max(MIN_PAGES, MIN_SHARE * pages) pages; main blocks are kept, else plain ones.  A main
  element that consists of such runs alone stays;
* inside an article, runs on max(MIN_PAGES, ARTICLE_SHARE * pages) pages, such as share lines, unless they are more than MOST_DROPPED of
  the article: that is a copy, not boilerplate.

Shares are those of a host's distinct streams, whatever its size: pages with equal streams count once.  A host of up to GROUP_PAGES
pages is one group.  A larger one is dealt by stream into groups, and their counts are put together exactly: a run on a share of a host's
streams is on that share in one group at least, so each group's suffix array gives its runs of the lower share, all groups
count all runs that any of them gave, and the sums decide for each page.  Streams with more than GROUP_PAGES copies leave one part of
them in the group; the others are dealt over parts that count nothing.

Defined cases: null or empty html gives the empty text; a null or malformed url is a host of its own; a null id stays null;
repeated rows are repeated; an empty table gives an empty result; other columns are not read; of equal blocks all or none stay.
"""

from __future__ import annotations

import hashlib
import html as html_lib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import if_small, map_arrow, read_table, write_read
from provspark.llm.tokens import filled

RUN_TOKENS = 8
GROUP_PAGES = 1000
MIN_PAGES, MIN_SHARE = 3, 0.02
#: Inside articles: the share of pages from which a run is boilerplate, and the most of an article that may go.
ARTICLE_SHARE, MOST_DROPPED = 0.5, 0.3
#: A block is boilerplate if repeated runs cover this share of its tokens.
COVERED = 0.8

# Names of the HTML standard and usual names of page parts.
RAW = {"script", "style", "noscript", "template", "iframe", "object", "svg", "math", "canvas", "audio", "video", "textarea", "select", "title", "xmp", "noembed", "noframes"}
CHROME = {"nav", "footer", "aside", "form", "button", "dialog", "menu", "head", "fieldset", "datalist"}
BLOCK = {"address", "article", "aside", "blockquote", "body", "caption", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "head", "header", "hgroup", "hr", "html", "legend", "li", "main", "menu", "nav", "ol", "p", "pre", "search", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul"}
#: Elements whose start and end are tracked; those with optional end tags are not.
NESTING = {"address", "article", "aside", "blockquote", "button", "center", "datalist", "details", "dialog", "div", "dl", "fieldset", "figure", "footer", "form", "head", "header", "hgroup", "main", "menu", "nav", "ol", "search", "section", "table", "ul", "span"}
#: Class names and ids, whole ones, of adverts and comments; and of other page parts, which count outside articles.
ADVERT_NAMES = {"ad", "ads", "advert", "adverts", "advertisement", "advertisements", "sponsored", "comment", "comments", "comment-list", "commentlist", "comments-area", "disqus_thread"}
PART_NAMES = {"sidebar", "navbar", "nav", "navigation", "menu", "breadcrumb", "breadcrumbs", "header", "masthead", "footer", "banner", "promo", "cookie-notice", "cookie-banner", "cookie-consent", "cookies", "notice", "newsletter", "popup", "modal", "pagination", "pager", "toolbar", "related", "recommended", "share", "social"}
CHROME_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "menu", "menubar"}
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
ATTRIBUTE = re.compile(r"\b(class|id|role|itemprop|hidden|aria-hidden)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
RAW_END = {t: re.compile(rf"</{t}\b[^>]*>?", re.I) for t in RAW}

ARTICLE, MAIN, PLAIN, AWAY = 3, 2, 1, 0
#: Chrome that may wrap a whole page, and article or main elements inside it, while a page is read.
SHELL, INNER = -1, 4
SOFT = "p"


def role_of(tag: str, attributes: str, inside: bool) -> int | None:
    """What an element makes of its content, None if nothing new; ``inside``: in an article or main element."""
    if tag in CHROME and tag not in ("form", "fieldset") or tag == "header" and not inside:
        return AWAY
    new = ARTICLE if tag == "article" else MAIN if tag == "main" else SHELL if tag in ("form", "fieldset") else None
    if attributes:
        found = {m[1].lower(): m[2] or m[3] or m[4] or "" for m in ATTRIBUTE.finditer(attributes)}
        role = found.get("role", "").lower()
        if role in CHROME_ROLES or "hidden" in found or found.get("aria-hidden") == "true":
            return AWAY
        names = {*found.get("class", "").lower().split(), found.get("id", "").lower().strip()}
        if names & ADVERT_NAMES:
            return AWAY
        if role == "article" or found.get("itemprop", "").lower() == "articlebody":
            new = ARTICLE
        elif role == "main":
            new = MAIN
        elif new is None and not inside and names & PART_NAMES:
            new = SHELL
    return new


def inside_of(role: int, new: int | None) -> int:
    """The role inside an element that says ``new`` where ``role`` held."""
    if new is None or role == AWAY:
        return role
    if new == AWAY or role in (ARTICLE, INNER) and new == SHELL:
        return AWAY
    if role == SHELL:
        return INNER if new in (ARTICLE, MAIN) else SHELL
    return new if new == SHELL else max(role, new)


def blocks_of(page: str) -> list[tuple[str, int]]:
    """(text, role) of a page's blocks in order; references decoded, white space single."""
    out: list[tuple[str, int]] = []
    parts: list[str] = []
    stack: list[tuple[str, int]] = []
    role, at, size = PLAIN, 0, len(page)

    def close() -> None:
        if parts:
            text = " ".join(html_lib.unescape("".join(parts)).split())
            if text:
                out.append((text, role))
            parts.clear()

    while at < size:
        m = TOKEN.search(page, at)
        if m is None:
            parts.append(page[at:])
            break
        if m.start() > at:
            parts.append(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA["):
                parts.append(m[0][9:].removesuffix("]]>").replace("&", "&amp;"))
            continue
        tag, end = m[2].lower(), bool(m[1])
        if tag in RAW:
            if not end and not m[3].endswith("/"):
                stop = RAW_END[tag].search(page, at)
                at = stop.end() if stop else size
            continue
        if tag in BLOCK:
            close()
            if stack and stack[-1][0] == SOFT:  # a paragraph or item ends where any block starts or ends
                role = stack.pop()[1]
        elif tag in ("br", "wbr", "img", "input"):
            parts.append(" " if tag != "wbr" else "")
        if tag in NESTING:
            if not end:
                if not m[3].endswith("/"):
                    now = inside_of(role, role_of(tag, m[3], role >= MAIN))
                    if now != role and tag == "span":
                        close()
                    stack.append((tag, role))
                    role = now
            else:
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] == tag:
                        back = stack[i][1]
                        if tag == "span" and back != role:
                            close()
                        role = back
                        del stack[i:]
                        break
        elif tag in BLOCK and m[3] and not end and role not in (AWAY, SHELL) and role_of(tag, m[3], role >= MAIN) in (AWAY, SHELL):
            stack.append((SOFT, role))
            role = AWAY
    close()
    inner = AWAY if any(r in (ARTICLE, MAIN) for _, r in out) else ARTICLE
    return [(t, inner if r == INNER else max(r, AWAY)) for t, r in out]


def parsed(pages: DataFrame, id_col: str, url_col: str, html_col: str, texts: bool = True) -> DataFrame:
    """Rows (page_id, url, stream, host) and, if wished, (texts, roles) of blocks that are not away; ``stream`` is the digest of all tokens."""
    kind = pages.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        blocks = [[b for b in blocks_of(page) if b[1] != AWAY] for page in filled(batch.column("html")).to_pylist()]
        stream = pa.array([hashlib.blake2b(" ".join(t for t, _ in page).encode(), digest_size=16).digest() for page in blocks], pa.binary())
        out = {"page_id": batch.column("page_id"), "url": batch.column("url"), "stream": stream}
        if texts:
            out["texts"] = pa.array([[t for t, _ in page] for page in blocks], pa.list_(pa.string()))
            out["roles"] = pa.array([[r for _, r in page] for page in blocks], pa.list_(pa.int8()))
        return pa.RecordBatch.from_pydict(out)

    schema = f"page_id {kind}, url string, stream binary" + (", texts array<string>, roles array<tinyint>" if texts else "")
    rows = map_arrow(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html")), schema, "html", per_slice)
    return rows.withColumn("host", host_of("url"))


def host_of(url: str) -> F.Column:
    return F.coalesce(F.lower(F.regexp_extract(F.col(url).cast("string"), r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1)), F.lit(""))


def suffix_ranks(tokens: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, rank) of a token stream sorted to ``depth`` tokens by doubling; equal ranks share a prefix of that length.

    Tokens are not negative; the first step takes as many of them as 62 bits hold.
    """
    n = len(tokens)
    bits = (int(tokens.max()) + 1).bit_length() if n else 1
    reach = max(1, min(depth, 62 // bits))
    key = np.zeros(n, np.int64)
    for j in range(reach):
        key <<= bits
        key[: max(n - j, 0)] += tokens[j:].astype(np.int64) + 1
    while True:
        order = np.argsort(key)
        ordered = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.concatenate([[0], np.cumsum(ordered[1:] != ordered[:-1])]) if n else []
        if reach >= depth:
            return order, rank
        step = min(reach, depth - reach)
        later = np.full(n, -1, np.int64)
        later[: max(n - step, 0)] = rank[step:]
        key, reach = rank * (n + 1) + later + 1, reach + step


def run_pages(tokens: np.ndarray, page: np.ndarray, run: int) -> tuple[np.ndarray, np.ndarray]:
    """(starts, distinct pages) of all runs of ``run`` tokens; ``page`` is the page of each token, and a run does not cross pages."""
    n = len(tokens)
    if n < run:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    order, rank = suffix_ranks(tokens, run)
    whole = np.zeros(n, bool)
    whole[: n - run + 1] = page[: n - run + 1] == page[run - 1 :]
    at = order[whole[order]]
    if not len(at):
        return at, at
    # Suffixes with one prefix are neighbours in the array; count the distinct pages among them.
    pages = int(page.max()) + 1
    ranks, counts = np.unique(np.unique(rank[at] * pages + page[at]) // pages, return_counts=True)
    return at, counts[np.searchsorted(ranks, rank[at])]


def covered_by(starts: np.ndarray, run: int, n: int) -> np.ndarray:
    """Which of n tokens lie in a run that begins at one of the starts."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + run, -1)
    return np.cumsum(edge[:-1]) > 0


def repeated_cover(tokens: np.ndarray, page: np.ndarray, run: int, pages: int) -> np.ndarray:
    """Which tokens lie in a run of ``run`` tokens that stands on at least ``pages`` distinct pages."""
    starts, counts = run_pages(tokens, page, run)
    return covered_by(starts[counts >= pages], run, len(tokens))


class Streams:
    """The token streams of some pages: codes of their words, block by block."""

    def __init__(self, texts: pa.ListArray) -> None:
        page_at = texts.offsets.to_numpy().astype(np.int64)
        #: The blocks' texts, and where each page's begin.
        self.flat = texts.values.slice(page_at[0], page_at[-1] - page_at[0])
        self.page_at = page_at - page_at[0]
        split = pc.ascii_split_whitespace(self.flat)
        block_at = split.offsets.to_numpy().astype(np.int64)
        coded = split.values.slice(block_at[0], block_at[-1] - block_at[0]).dictionary_encode() if len(self.flat) else pa.array([], pa.string()).dictionary_encode()
        self.words, self.codes = coded.dictionary, coded.indices.to_numpy().astype(np.int64)
        #: Where the tokens of each block, and those of each page, begin; and the page of each token.
        self.block_at = block_at - block_at[0] if len(self.flat) else np.zeros(1, np.int64)
        self.bounds = self.block_at[self.page_at]
        self.page = np.repeat(np.arange(len(texts)), np.diff(self.bounds))

    def frequent(self, run: int, pages: float) -> list[str]:
        """The runs, words joined by a space, that stand on at least ``pages`` of the pages."""
        starts, counts = run_pages(self.codes, self.page, run)
        starts = starts[counts >= pages]
        found = np.unique(self.codes[starts[:, None] + np.arange(run)], axis=0)
        words = self.words.to_pylist()
        return [" ".join(words[c] for c in row) for row in found.tolist()]

    def places(self, runs: list[str], run: int) -> tuple[np.ndarray, np.ndarray]:
        """(starts, index of the run) of all places where one of the distinct runs stands within a page."""
        n, kinds = len(self.codes), len(self.words)
        none = np.zeros(0, np.int64)
        if n < run or not runs:
            return none, none
        code = pc.fill_null(pc.index_in(pa.array([w for r in runs for w in r.split(" ")], pa.string()), value_set=self.words), -1).to_numpy().astype(np.int64).reshape(-1, run)
        known = np.flatnonzero((code >= 0).all(axis=1))
        code = code[known]
        at = np.flatnonzero(self.page[: n - run + 1] == self.page[run - 1 :])
        prefix, state = np.zeros(len(known), np.int64), np.zeros(len(at), np.int64)
        for j in range(run):
            if not len(known) or not len(at):
                return none, none
            keys, prefix = np.unique(prefix * kinds + code[:, j], return_inverse=True)
            own = state * kinds + self.codes[at + j]
            state = np.minimum(np.searchsorted(keys, own), len(keys) - 1)
            same = keys[state] == own
            at, state = at[same], state[same]
        which = np.empty(len(known), np.int64)
        which[prefix] = known
        return at, which[state]


def needed(streams: int, share: float, min_pages: int) -> int:
    """The distinct streams that make a run boilerplate on a host of so many."""
    return max(min_pages, int(np.ceil(share * streams)))


def kept_blocks(s: Streams, roles: pa.ListArray, cover: np.ndarray, common: np.ndarray, covered: float) -> tuple[list[str], list[int], list[int]]:
    """(text, repeated tokens, tokens) of each page, from the tokens that runs of the lower and of the article share cover."""
    role = roles.values.to_numpy()[roles.offsets[0].as_py() : roles.offsets[-1].as_py()]
    size, page_at = np.diff(s.block_at), s.page_at

    def boilerplate(over: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(covered tokens before each place, which blocks are covered)."""
        total = np.concatenate([[0], np.cumsum(over)])
        return total, total[s.block_at[1:]] - total[s.block_at[:-1]] >= covered * np.maximum(size, 1)

    total, boiler = boilerplate(cover)
    _, often = boilerplate(common)
    words = s.flat.to_pylist()
    out = []
    for i in range(len(page_at) - 1):
        own = np.arange(page_at[i], page_at[i + 1])
        kept = own[role[own] == ARTICLE]
        if len(kept):
            if size[kept[often[kept]]].sum() <= MOST_DROPPED * size[kept].sum():
                kept = kept[~often[kept]]
        else:
            main = own[role[own] == MAIN]
            pool = main if len(main) else own
            kept = pool[~boiler[pool]]
            kept = kept if len(kept) else main
        out.append("\n".join(words[b] for b in kept))
    return out, (total[s.bounds[1:]] - total[s.bounds[:-1]]).tolist(), np.diff(s.bounds).tolist()


def extract_host(texts: pa.ListArray, roles: pa.ListArray, run: int, min_pages: int, min_share: float, covered: float) -> tuple[list[str], list[int], list[int]]:
    """(text, repeated tokens, tokens) of each page of a whole host."""
    s = Streams(texts)
    # Pages with equal streams count as one: all but the first are left out of the array, and share its cover.
    first: dict[bytes, int] = {}
    same = [first.setdefault(s.codes[a:b].tobytes(), i) for i, (a, b) in enumerate(zip(s.bounds, s.bounds[1:]))]
    once = np.array([i == k for i, k in enumerate(same)], bool)
    mask = once[s.page]
    starts, counts = run_pages(s.codes[mask], s.page[mask], run)

    def cover(share: float) -> np.ndarray:
        over = np.zeros(len(s.codes), bool)
        over[mask] = covered_by(starts[counts >= needed(int(once.sum()), share, min_pages)], run, int(mask.sum()))
        for i, k in enumerate(same):
            if k != i:
                over[s.bounds[i] : s.bounds[i + 1]] = over[s.bounds[k] : s.bounds[k + 1]]
        return over

    return kept_blocks(s, roles, cover(min_share), cover(ARTICLE_SHARE), covered)


def extract_pages(texts: pa.ListArray, roles: pa.ListArray, runs: list[dict], streams: int, run: int, min_pages: int, min_share: float, covered: float) -> tuple[list[str], list[int], list[int]]:
    """(text, repeated tokens, tokens) of each of some pages of a host whose repeated runs are known with their counts."""
    s = Streams(texts)
    starts, which = s.places([r["run"] for r in runs], run)
    counts = np.array([r["n"] for r in runs], np.int64)[which]

    def cover(share: float) -> np.ndarray:
        return covered_by(starts[counts >= needed(streams, share, min_pages)], run, len(s.codes))

    return kept_blocks(s, roles, cover(min_share), cover(ARTICLE_SHARE), covered)


def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[tuple[str, int], pa.RecordBatch]]:
    """((host, part), rows) of sorted batches; a part's rows may come in some pieces."""
    for batch in batches:
        keys = list(zip(batch.column("host").to_pylist(), batch.column("part").to_pylist()))
        a = 0
        for b in range(1, len(keys) + 1):
            if b == len(keys) or keys[b] != keys[a]:
                yield keys[a], batch.slice(a, b - a)
                a = b


def column_of(held: list[pa.RecordBatch], name: str) -> pa.Array:
    out = pa.Table.from_batches(held).column(name).combine_chunks()
    return out.chunk(0) if isinstance(out, pa.ChunkedArray) else out


def group_streams(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[str, int, list[dict], Streams | None, int]]:
    """(host, part, runs of the mark, distinct streams, their number) of each part of an open host; no streams where a part counts nothing."""
    mark, runs, held, seen = None, [], [], set()

    def group():
        return *mark, runs, Streams(column_of(held, "texts")) if held else None, len(seen)

    for key, piece in pieces(batches):
        if key != mark:
            if mark is not None:
                yield group()
            mark, runs, held, seen = None, [], [], set()
        if not piece.column("open")[0].as_py():
            continue
        mark = key
        if piece.column("page")[0].as_py() == 0 and "runs" in piece.schema.names:
            runs = piece.column("runs")[0].as_py() or []
        if key[1] < 0:
            continue
        new = []
        for is_page, stream in zip(piece.column("page").to_pylist(), piece.column("stream").to_pylist()):
            new.append(is_page == 1 and stream not in seen)
            if new[-1]:
                seen.add(stream)
        if any(new):
            held.append(piece.filter(pa.array(new)))
    if mark is not None:
        yield group()


COUNTS = "host string, part int, run string, n long"


def counts_batch(host: str, part: int, streams: int, runs: list[str], counts: list[int]) -> pa.RecordBatch:
    """A part's runs with their counts, and a row without a run for the number of its streams."""
    m = len(runs) + 1
    return pa.RecordBatch.from_arrays([pa.array([host] * m, pa.string()), pa.array([part] * m, pa.int32()), pa.array([None, *runs], pa.string()), pa.array([streams, *counts], pa.int64())], names=["host", "part", "run", "n"])


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", run: int = RUN_TOKENS, group_pages: int = GROUP_PAGES, min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE, covered: float = COVERED) -> DataFrame:
    """Rows (page_id, url, text, n_chars, n_tokens, repeated_tokens), one for each page; ``group_pages`` changes none of them."""
    kind = pages.schema[id_col].dataType.simpleString()
    low = min(min_share, ARTICLE_SHARE)
    key = F.xxhash64("page_id", "url")
    # What each host has: pages, distinct streams, and the streams of more copies than a group has pages.
    streams = parsed(pages, id_col, url_col, html_col, texts=False).groupBy("host", "stream").agg(F.count("*").alias("n"), F.min(key).alias("first"))
    many = F.when(F.col("n") > group_pages, F.struct("stream", F.ceil(F.col("n") / group_pages).cast("long").alias("copies"), "first"))
    hosts = write_read(streams.groupBy("host").agg(F.sum("n").alias("n"), F.count("*").alias("streams"), F.sum(F.least("n", F.lit(group_pages))).alias("held"), F.collect_list(many).alias("many")), "hosts")
    # Hosts of more than one group: few, and broadcast within a bound, so pages are shuffled once.  Groups have a tenth of
    # group_pages distinct streams or more, or hold them all.
    groups = F.greatest(F.lit(1), F.least(F.ceil(F.col("held") / group_pages), F.ceil(F.col("streams") * 10 / group_pages))).cast("int")
    opened = hosts.filter(F.col("n") > group_pages).select("host", groups.alias("groups"), F.lit(True).alias("open"), "many")
    n_open, n_many, n_pages = hosts.agg(F.count(F.when(F.col("n") > group_pages, 1)), F.sum(F.size("many")), F.sum("n")).first()
    # Partitions by the number of pages, so that no task's share grows with the input.
    partitions = max(int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-(n_pages or 0) // group_pages))
    copied = opened.select("host", F.explode("many").alias("m")).select("host", "m.stream", "m.copies", "m.first")
    other_part = lambda nth: (-1 - F.pmod(F.xxhash64("stream", nth), F.lit(1 << 30))).cast("int")
    rows = parsed(pages, id_col, url_col, html_col).join(if_small(opened.drop("many"), n_open), "host", "left").join(if_small(copied, n_many or 0), ["host", "stream"], "left")
    # The copy with the least key stays in the group, whatever the others do.
    rows = rows.withColumn("nth", F.coalesce(F.pmod(F.pmod(key, "copies") - F.pmod("first", "copies"), "copies"), F.lit(0).cast("long")))
    rows = rows.withColumn("part", F.when(F.col("nth") > 0, other_part(F.col("nth"))).otherwise(F.pmod(F.xxhash64("stream"), F.coalesce("groups", F.lit(1))).cast("int")))
    rows = rows.select("host", "part", F.lit(1).alias("page"), F.coalesce("open", F.lit(False)).alias("open"), "page_id", "url", "stream", "texts", "roles")
    # Each part of an open host has a row in front that carries the host's runs to it.
    in_groups = opened.select("host", F.explode(F.sequence(F.lit(0), F.col("groups") - 1)).alias("part"))
    in_others = copied.select("host", "stream", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies") - 1)).alias("nth")).select("host", other_part(F.col("nth")).alias("part"))
    marks = in_groups.union(in_others).distinct().select("host", "part", F.lit(0).alias("page"), F.lit(True).alias("open"))
    dealt = rows.unionByName(marks, allowMissingColumns=True).repartition(partitions, "host", "part")
    in_order = lambda df: df.sortWithinPartitions("host", "part", "page")

    def carried(counted: DataFrame, share: float) -> DataFrame:
        """The dealt rows, marks with the number of streams of their hosts and the runs of that share of them.

        A left join, so that the one shuffle serves all; by merging, as a host's runs go to each of its parts and may be many.
        """
        by_run = counted.groupBy("host", "run").agg(F.sum("n").alias("n"), F.collect_list(F.when(F.col("run").isNull(), F.col("part"))).alias("parts"))
        host = by_run.groupBy("host").agg(F.max(F.when(F.col("run").isNull(), F.col("n"))).alias("streams"), F.flatten(F.collect_list("parts")).alias("parts"), F.collect_list(F.when(F.col("run").isNotNull(), F.struct("run", "n"))).alias("runs"))
        host = host.withColumn("runs", F.filter("runs", lambda r: r["n"] >= F.lit(share) * F.col("streams") - F.lit(1e-6)))
        to_parts = host.select("host", F.explode("parts").alias("part"), "streams", "runs").hint("merge")
        mark = F.col("page") == 0
        return in_order(dealt.join(to_parts, ["host", "part"], "left").withColumn("streams", F.when(mark, F.col("streams"))).withColumn("runs", F.when(mark, F.col("runs"))))

    def give(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for host, part, _, s, n in group_streams(batches):
            found = s.frequent(run, low * n - 1e-6) if s else []
            yield counts_batch(host, part, n, found, [0] * len(found))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for host, part, runs, s, n in group_streams(batches):
            names = [r["run"] for r in runs] if s else []
            at, which = s.places(names, run) if s else (np.zeros(0, np.int64),) * 2
            pairs = np.unique(which * max(n, 1) + s.page[at]) // max(n, 1) if s else which
            each, counts = np.unique(pairs, return_counts=True)
            yield counts_batch(host, part, n, [names[i] for i in each], counts.tolist())

    def result(held: list[pa.RecordBatch], found: tuple[list[str], list[int], list[int]]) -> pa.RecordBatch:
        text, repeated, tokens = found
        return pa.RecordBatch.from_arrays([column_of(held, "page_id"), column_of(held, "url"), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64()), pa.array(tokens, pa.int64()), pa.array(repeated, pa.int64())], names=["page_id", "url", "text", "n_chars", "n_tokens", "repeated_tokens"])

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        mark, runs, n = None, [], 0

        def whole() -> Iterator[pa.RecordBatch]:
            if held:
                yield result(held, extract_host(column_of(held, "texts"), column_of(held, "roles"), run, min_pages, min_share, covered))

        for key, piece in pieces(batches):
            if key != mark:
                yield from whole()
                mark, held = key, []
            if not piece.column("open")[0].as_py():
                held.append(piece)
                continue
            if piece.column("page")[0].as_py() == 0:
                n, runs = piece.column("streams")[0].as_py() or 0, piece.column("runs")[0].as_py() or []
                runs = [r for r in runs if r["n"] >= needed(n, low, min_pages)]
                piece = piece.slice(1)
            if piece.num_rows:
                yield result([piece], extract_pages(column_of([piece], "texts"), column_of([piece], "roles"), runs, n, run, min_pages, min_share, covered))
        yield from whole()

    if n_open:
        given = in_order(dealt).mapInArrow(give, COUNTS)
        ready = carried(carried(given, 0.0).mapInArrow(count, COUNTS), low)
    else:
        ready = in_order(dealt)
    return ready.mapInArrow(finish, f"page_id {kind}, url string, text string, n_chars long, n_tokens long, repeated_tokens long")


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(read_table(spark, sf_dir, "pages"))
