"""Main text of web pages by wrapper induction.

A page is cut into a tree of elements; consecutive siblings of one signature (tag and classes) fold into one repeated node.
The most frequent tree of a host is its reference; every other tree is aligned to it by simple tree matching (the largest
order-preserving match of children, level by level).  Text is compared per aligned node over the host's distinct pages: a
text that SHARE of them show at one node is template and goes, varying slots are content.  All blocks take part, also those
whose markup tells what they are for, and `induced` says how many blocks of a page the alignment alone took out.

Menus, adverts and comments may vary from page to page, where no alignment can tell them from the article; and a host may
have too few pages.  There element names, roles and class words decide: a slot for a menu, header, footer, sidebar, notice,
advert, form, script, style or reader comments is template even where its text varies.  The article and main elements bound
the content where they hold most of the text that is left (a page may have but a teaser in an article element).

Statistics are grouped sums over all pages with map-side combine (one row per host, node and text hash); a host with a third
of all pages is one key of tiny rows.  The template table (a tree and a few hashes per host) is shipped to the tasks when its
checked size is at most TEMPLATE_BYTES and joined by host otherwise.

Defined results: a null or empty html gives empty text; broken or cut markup is read as far as it goes, an element that is
never closed hides nothing but an open script or style; blocks nested deeper than DEPTH are compared by their plain place;
a null or odd url is host ""; hosts with fewer than MIN_PAGES distinct pages have no constant text; repeated rows give repeated
results (they count once in the statistics); input columns named like a result column are replaced by it; an empty table
gives no rows.
"""

from __future__ import annotations

import html
import json
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, safe_prefix, table

MIN_PAGES, SHARE, TEMPLATE_BYTES, DEPTH = 6, 0.8, 64 << 20, 200

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^\"'>]|\"[^\"]*\"|'[^']*')*+)(?:>|\Z)", re.S)
ATTR = re.compile(r"([a-zA-Z_:][-a-zA-Z0-9_:.]*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
SPLIT = re.compile(r"[^a-z0-9]+")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: elements whose inside is no text of the page; the open ones end with the page
RAW = frozenset("script style template textarea title svg iframe select".split())
OPEN = frozenset(("script", "style"))
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody tfoot thead tr ul caption".split())
CLOSES_P = BLOCK - {"html", "body"}
DROP = frozenset("nav footer aside form button input menu dialog fieldset head".split())
DROP_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())
DROP_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising adsbygoogle sponsor sponsored sponsors promo promotion banner cookie cookies consent gdpr notice notices alert sidebar aside nav navbar "
    "navigation menu menus breadcrumb breadcrumbs footer masthead topbar toolbar comment comments commentlist disqus reply replies respond share sharing social related recommended newsletter "
    "subscribe subscription signup popup modal overlay pagination pager login search widget widgets".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())


class Node:
    __slots__ = ("sig", "tag", "drop", "kids", "parts", "up", "last")

    def __init__(self, sig, tag, drop, up):
        self.sig, self.tag, self.drop, self.up = sig, tag, drop, up
        self.kids, self.parts, self.last = [], [], None


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): html.unescape(m[2] or m[3] or m[4] or "") for m in ATTR.finditer(raw)} if raw.strip(" /\t\r\n") else {}


def _judge(tag: str, attrs: dict[str, str], inside: bool) -> tuple[str, bool]:
    """The signature of an element and whether it is there for something else than the article."""
    names = (attrs.get("class", "") + " " + attrs.get("id", "")).lower() if attrs else ""
    sig = tag + "".join("." + x for x in sorted(set(attrs.get("class", "").lower().split()))) if attrs else tag
    if tag in DROP or tag in ("header", "noscript") and not inside:
        return sig, True
    if attrs:
        if attrs.get("role", "").lower() in DROP_ROLES or "hidden" in attrs or attrs.get("aria-hidden") == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower():
            return sig, True
        words = SPLIT.split(names)
        if tag not in ("html", "body", "main", "article") or "comment" in words or "comments" in words:
            if not DROP_WORDS.isdisjoint(words) or ("header" in words and not inside):
                return sig, True
    return sig, False


def parse(page: str) -> Node:
    """The element tree with the decoded text pieces of each block, in page order."""
    root = Node("#", "#", False, None)
    at, inside, pos, end = root, 0, 0, len(page)
    lower = None
    while pos < end:
        m = TAG.search(page, pos)
        text = page[pos : m.start()] if m else page[pos:]
        if text:
            cut = text.rfind("<") if not m else -1
            at.parts.append(html.unescape(text[:cut] if cut >= 0 and re.match(r"<[a-zA-Z/!]", text[cut:]) else text))
        if not m:
            break
        pos, tag = m.end(), (m[2] or "").lower()
        if not tag:
            continue
        if m[1]:
            up = at
            while up is not root and up.tag != tag:
                up = up.up
            while up is not root and at is not up.up:
                inside -= at.tag in ("article", "main")
                at = at.up
            continue
        if tag in RAW and not m[3].rstrip().endswith("/"):
            lower = page.lower() if lower is None else lower
            close = lower.find("</" + tag, pos)
            if close < 0:
                if tag in OPEN:
                    break
                continue
            stop = page.find(">", close)
            pos = end if stop < 0 else stop + 1
            continue
        if tag in VOID:
            at.parts.append(None if tag == "hr" else " ")
            continue
        if tag in CLOSES_P:
            open_ones = ("p", tag) if tag in ("li", "dd", "dt", "tr") else ("p",)
            up = at
            while up is not root and up.tag not in BLOCK:
                up = up.up
            if up.tag in open_ones:
                at = up.up
        sig, drop = _judge(tag, _attributes(m[3]), inside > 0)
        kid = Node(sig, tag, drop or at.drop, at)
        at.kids.append(kid)
        at.parts.append(kid)
        if tag in ("article", "main"):
            inside += 1
        if tag in ("td", "th"):
            kid.parts.append(" ")
        at = kid
    return root


def blocks(root: Node) -> list[tuple[tuple, str, bool, bool]]:
    """(node path, text, dropped, in the article) of every block with text.  A path is the tuple of folded child numbers."""
    out, buffer, where = [], [], None

    def flush():
        nonlocal buffer
        text = " ".join("".join(buffer).split())
        if text:
            out.append((*where[:1], text, *where[1:]))
        buffer = []

    todo = [("open", root, (), 0)]
    while todo:
        step, n, path, scope = todo.pop()
        if step == "text":
            if not buffer:
                where = (path, n[1], scope)
            elif where != (path, n[1], scope):
                flush()
                where = (path, n[1], scope)
            buffer.append(n[0])
        elif step == "cut":
            if buffer:
                flush()
        else:
            numbers, seq, prev, k = {}, [], None, -1
            for kid in n.kids:
                if kid.tag not in BLOCK:
                    numbers[id(kid)] = path
                    continue
                if kid.sig != prev:
                    k, prev = k + 1, kid.sig
                numbers[id(kid)] = (*path, k)
            for part in n.parts:
                if part is None:
                    seq.append(("cut", None, None, None))
                elif isinstance(part, str):
                    seq.append(("text", (part, n.drop), path, scope))
                else:
                    sub = 2 if part.tag == "article" else max(scope, 1) if part.tag == "main" else scope
                    if part.tag in BLOCK:
                        seq.append(("cut", None, None, None))
                    seq.append(("open", part, numbers[id(part)], sub))
                    if part.tag in BLOCK:
                        seq.append(("cut", None, None, None))
            todo.extend(reversed(seq))
    if buffer:
        flush()
    return out


def shape(root: Node) -> list:
    """The folded tree of block elements as nested lists [signature, children]."""

    def fold(nodes: list[Node]) -> list:
        kids = []
        for n in nodes:
            if n.tag in BLOCK:
                if kids and kids[-1][0] == n.sig:
                    kids[-1][1].extend(n.kids)
                else:
                    kids.append((n.sig, list(n.kids)))
        return kids

    def build(sig: str, nodes: list[Node], depth: int) -> list:
        return [sig, [build(s, k, depth + 1) for s, k in fold(nodes)] if depth < DEPTH else []]

    return build("#", root.kids, 0)


def match(a: list, b: list) -> tuple[int, list]:
    """Simple tree matching of two trees with equal root signatures: size of the best match and its child pairs."""
    if a[0] != b[0]:
        return 0, []
    m, n = len(a[1]), len(b[1])
    sub = [[match(x, y) for y in b[1]] for x in a[1]]
    best = [[0] * (n + 1) for _ in range(m + 1)]
    for i in range(m):
        for j in range(n):
            best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + sub[i][j][0])
    pairs, i, j = [], m, n
    while i and j:
        if best[i][j] == best[i - 1][j]:
            i -= 1
        elif best[i][j] == best[i][j - 1]:
            j -= 1
        else:
            pairs.append((i - 1, j - 1, sub[i - 1][j - 1][1]))
            i, j = i - 1, j - 1
    return best[m][n] + 1, pairs


def alignment(tree: str, reference: str) -> dict:
    """Paths of a tree's nodes -> paths of the reference's nodes they match."""
    out, todo = {(): ()}, [((), (), match(json.loads(tree), json.loads(reference))[1])]
    while todo:
        p, q, pairs = todo.pop()
        for i, j, below in pairs:
            out[(*p, i)] = (*q, j)
            todo.append(((*p, i), (*q, j), below))
    return out


def _remembered(cache: dict, tree: str, reference: str) -> dict:
    """alignment() with a bounded memory: a host has few distinct trees."""
    key = (tree, reference)
    if key not in cache:
        if len(cache) > 20_000:
            cache.clear()
        cache[key] = alignment(tree, reference)
    return cache[key]


def _place(path: tuple, aligned: dict) -> str:
    """The reference node of a path, or the path below its deepest matched part."""
    return "/".join(map(str, aligned[path])) if path in aligned else "?" + "/".join(map(str, path))


def _signature(tree: list, path: tuple) -> str:
    """The element signatures from the root of a folded tree down a path."""
    out = []
    for k in path[:DEPTH]:
        tree = tree[1][k] if k < len(tree[1]) else ["", []]
        out.append(tree[0])
    return "/".join(out)


def judge(root: Node, ref: str, fixed: frozenset, cache: dict):
    """A function (path, text) -> whether a block of the page stays, given its host's template.

    A block that the alignment leaves over (an element came between, so its siblings fold otherwise) is template where
    the same text is constant under the same signatures.
    """
    tree = shape(root)
    to = _remembered(cache, json.dumps(tree, separators=(",", ":")), ref)
    if (ref, fixed) not in cache:
        whole = json.loads(ref)
        placed = (x.split(":") for x in fixed if not x.startswith("?"))
        cache[ref, fixed] = {f"{_signature(whole, tuple(int(k) for k in node.split('/') if k))}:{h}" for node, h in placed}
    under = cache[ref, fixed]

    def stays(path, text):
        h = _hash(text)
        return f"{_place(path, to)}:{h}" not in fixed and (path in to or f"{_signature(tree, path)}:{h}" not in under)

    return stays


def main_text(found: list, keep) -> str:
    """The blocks that stay, of the article and main elements if these hold at least half of the text, else of the page."""
    left = [(t, s) for path, t, drop, s in found if not drop and keep(path, t)]
    bounded = [t for t, s in left if s > 0]
    whole = sum(len(t) for t, _ in left)
    return "\n\n".join(bounded if bounded and 2 * sum(map(len, bounded)) >= whole else [t for t, _ in left])


def induced(found: list, keep) -> int:
    """Blocks that only the alignment takes out."""
    return sum(not drop and not keep(path, t) for path, t, drop, _ in found)


def _hash(text: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text) - (1 << 63)


def host_of(url):
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def templates(pages: DataFrame, url: str = "url", page: str = "html") -> DataFrame:
    """host -> reference tree (JSON) and constants, an array of "node:hash"."""

    def scan(batches):
        for b in batches:
            rows = []
            for h, p in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                root = parse(p or "")
                found = blocks(root)
                rows.append((h, json.dumps(shape(root), separators=(",", ":")), ["/".join(map(str, path)) for path, *_ in found], [_hash(t) for _, t, *_ in found]))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.list_(pa.string()), pa.list_(pa.int64())))], names=["host", "tree", "paths", "hashes"])

    slim = pages.select(host_of(F.col(url)).alias("host"), F.col(page).alias("page"))
    seen = slim.mapInArrow(scan, "host string, tree string, paths array<string>, hashes array<bigint>")
    seen = materialize(seen.withColumn("id", F.xxhash64("hashes")).groupBy("host", "id").agg(*[F.first(c).alias(c) for c in ("tree", "paths", "hashes")]))  # distinct pages
    refs = seen.groupBy("host", "tree").agg(F.count(F.lit(1)).alias("n")).groupBy("host").agg(F.max_by("tree", F.struct("n", "tree")).alias("ref"), F.sum("n").alias("pages"))

    def align(batches):
        cache = {}
        for b in batches:
            out = []
            for h, tree, ref, paths, hashes in zip(*[b.column(i).to_pylist() for i in range(5)]):
                to = _remembered(cache, tree, ref)
                out += {(h, _place(tuple(int(x) for x in p.split("/") if x), to), x) for p, x in zip(paths, hashes)}
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate((pa.string(), pa.string(), pa.int64()))], names=["host", "node", "h"])

    refs = materialize(refs)
    many = refs.where(F.col("pages") >= MIN_PAGES)
    slots = seen.join(many, "host").select("host", "tree", "ref", "paths", "hashes").mapInArrow(align, "host string, node string, h bigint")
    counts = slots.groupBy("host", "node", "h").agg(F.count(F.lit(1)).alias("n")).join(many.select("host", "pages"), "host")
    fixed = counts.where(F.col("n") >= SHARE * F.col("pages")).groupBy("host").agg(F.sort_array(F.collect_list(F.concat_ws(":", "node", "h"))).alias("fixed"))  # at most 1 / SHARE texts a node
    return refs.join(fixed, "host", "left").select("host", "ref", F.coalesce("fixed", F.array().cast("array<string>")).alias("fixed"))


def extract(pages: DataFrame, url: str = "url", page: str = "html", out: str = "text", count: str = "n_induced") -> DataFrame:
    """pages without the html column, with the main text and the number of blocks that the alignment alone took out."""
    p = safe_prefix(pages, "wi")
    found = materialize(templates(pages, url, page).where(F.size("fixed") > 0))
    size = found.agg(F.coalesce(F.sum(F.length("host") + F.length("ref") + F.length(F.concat_ws(",", "fixed"))), F.lit(0))).first()[0]
    keep = [c for c in pages.columns if c not in (page, out, count)]
    rows = pages.select(*keep, F.col(page).alias(f"{p}page"), host_of(F.col(url)).alias(f"{p}host"))
    small = size <= TEMPLATE_BYTES
    shipped = pages.sparkSession.sparkContext.broadcast({r.host: (r.ref, frozenset(r.fixed)) for r in found.collect()}) if small else None
    if not small:
        named = found.select(*[F.col(c).alias(f"{p}{c}") for c in ("host", "ref", "fixed")])
        rows = rows.join(named, f"{p}host", "left").select(*keep, *[f"{p}{c}" for c in ("page", "host", "ref", "fixed")])
    n = len(keep)

    def run(batches):
        cache = {}
        for b in batches:
            texts, gone = [], []
            refs = zip(b.column(n + 2).to_pylist(), b.column(n + 3).to_pylist()) if shipped is None else (shipped.value.get(h, (None, None)) for h in b.column(n + 1).to_pylist())
            for raw, (ref, fixed) in zip(b.column(n).to_pylist(), refs):
                root = parse(raw or "")
                found = blocks(root)
                if ref is None:
                    stays = lambda path, t: True
                else:
                    stays = judge(root, ref, frozenset(fixed), cache)
                texts.append(main_text(found, stays))
                gone.append(induced(found, stays))
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(texts, pa.string()), pa.array(gone, pa.int32())], names=[*keep, out, count])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pages.select(*keep).schema) + f", `{out}` string, `{count}` int"
    return rows.mapInArrow(run, schema)


def op4_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), "n_induced")
