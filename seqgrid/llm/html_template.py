"""Operator 7, HTML extraction by equivalence classes of template tokens.

Pages are tokenised into tags (name and attributes apart) and words. A token's role is the token in its path of open
elements. Roles with the same occurrence vector (how often they occur on each page of the host) form an equivalence
class. A class is valid when it has at least MIN_CLASS roles on enough pages (need()), when its roles keep one order
on every page (once each for every repetition), and when it nests with every valid class that is more widespread: of
two classes one never has a token of the other inside a repetition. The valid classes are the host's template; what
other tokens stand in a gap of it is a slot's value.

All of this is over all pages of a host, by three passes that read the pages and leave the small tables between them
in the shared folder:

1. pages are shuffled to blocks of a host (BLOCK_PAGES or BLOCK_BYTES, so a hot host is many tasks). A block tells, for
   the roles that share their vector with another role there, in how many pages they are and an order-free sum of
   hashes of (page, count). Sums over blocks are equal for equal vectors, so a host's classes follow by aggregation.
   Equal vectors are equal in every block, so no member of a class is left out where another is told.
2. a map of the pages, with their host's classes, reports the classes out of order and the pairs that don't nest.
3. a map of the pages, with their host's template, fills the slots.

Roles that stand on less than a quarter of TENTH of a block's pages are not told of from there (only hosts of more
than one block), so a class near the limit of need() can count too few pages; it is still kept or dropped as a whole.

Result: one row (page_id, host, slot, instance, value) for each non-empty slot value. slot names the template token
before the gap with its path, e.g. 'html/body/article/p>'; instance counts the slot's values on the page from 0.
Defined results: null html, and html without tokens, give no row; hosts with fewer than MIN_PAGES pages
(and urls without a host, which are grouped under '') have no template, and their page is one slot '' of its visible
words; repeated rows count as pages of their own and give their rows again; comments, scripts and styles are never
content. A path names its innermost DEPTH elements, with a hash of the outer ones where there are more.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import cut, load, mix

BLOCK_PAGES, BLOCK_BYTES, LEAST_PAGES = 512, 8 << 20, 64
MIN_PAGES, TENTH, ENOUGH, MIN_CLASS = 4, 0.1, 10, 2
DEPTH = 24
BROADCAST_BYTES, BROADCAST_HOSTS = 64 << 20, 1 << 20
RESULT = "page_id long, host string, slot string, instance int, value string"
_DROP = re.compile(r"<!--.*?(?:-->|$)|<(script|style)\b[^>]*>.*?(?:</\1\s*>|$)", re.S | re.I)
_TAG = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>|<![^>]*>")
_ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
_VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
_ENTITY = {"amp": "&", "lt": "<", "gt": ">", "quot": '"', "apos": "'", "nbsp": " "}
_ENT = re.compile(r"&(#x[0-9a-fA-F]{1,6}|#[0-9]{1,7}|[a-zA-Z]{2,8});")


def host_of(url: Column) -> Column:
    """Lower-cased host without user, port and a leading www. or m. label; '' when there is none."""
    host = F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))
    return F.coalesce(F.regexp_replace(host, r"^(www|m)\.", ""), F.lit(""))


def unescape(text: str) -> str:
    def one(m: re.Match) -> str:
        name = m[1]
        if name[0] != "#":
            return _ENTITY.get(name, m[0])
        code = int(name[2:], 16) if name[1] in "xX" else int(name[1:])
        return chr(code) if 0 < code < 0x110000 and not 0xD800 <= code < 0xE000 else m[0]

    return _ENT.sub(one, text) if "&" in text else text


def tokens(html: str) -> tuple[list[str], list[str]]:
    """Roles (token in its path) and the words they show ('' for markup), in order."""
    roles: list[str] = []
    shown: list[str] = []
    stack: list[str] = []
    chain = [0]  # chain[k]: a hash of the k outermost open elements
    path = ""
    at = 0

    def path_of() -> str:
        if len(stack) <= DEPTH:
            return "/".join(stack)
        return f"~{chain[len(stack) - DEPTH]:08x}/" + "/".join(stack[-DEPTH:])

    html = _DROP.sub(" ", html)

    def words(text: str) -> None:
        got = unescape(text).split()
        roles.extend([path + "|" + w for w in got])
        shown.extend(got)

    for m in _TAG.finditer(html):
        if m.start() > at:
            words(html[at : m.start()])
        at = m.end()
        name = m[2]
        if not name:
            roles.append("|" + m[0].lower())
            shown.append("")
            continue
        name = name.lower()
        if m[1]:
            if name in stack:  # an element left open inside it closes too
                while stack.pop() != name:
                    pass
                path = path_of()
            roles.append(path + "/" + name + "<")
            shown.append("")
            continue
        if name in ("p", "li", "tr", "td", "th", "option") and stack and stack[-1] == name:
            stack.pop()
            path = path_of()
        here = path + "/" + name if path else name
        roles.append(here + ">")
        shown.append("")
        if m[3].strip(" /"):
            for key, value in _ATTR.findall(m[3]):
                roles.append(f"{here}@{key.lower()}")
                shown.append("")
                if value:
                    roles.append(f"{here}@{key.lower()}|{value}")
                    shown.append("")
        if name not in _VOID and not m[3].endswith("/"):
            del chain[len(stack) + 1 :]
            chain.append(zlib.crc32(name.encode(), chain[len(stack)]))
            stack.append(name)
            path = here if len(stack) <= DEPTH else path_of()
    if at < len(html):
        words(html[at:])
    return roles, shown


def need(pages: int) -> int:
    """Pages on which a class must stand: half of a small host's, ENOUGH of them, or a tenth of a large one's."""
    return max(2, int(np.ceil(TENTH * pages)), min(int(np.ceil(pages / 2)), ENOUGH))


ROLES = "host string, role string, pages long, lo long, hi long, first_key long, place int"


def block_roles(keys: np.ndarray, pages: list[list[str]], least: int) -> list[tuple[str, int, int, int, int, int]]:
    """(role, pages, lo, hi, first_key, place) of the roles on at least so many pages whose occurrence vector another one shares.

    lo and hi sum 31 bits each of a hash of (page, count): their sums over a host can't overflow, and are the same in any order.
    """
    number: dict[str, int] = {}
    role = np.fromiter((number.setdefault(r, len(number)) for p in pages for r in p), np.int64)
    if not len(role):
        return []
    size = np.array([len(p) for p in pages])
    page = np.repeat(np.arange(len(pages)), size)
    pair, first, count = np.unique(role * len(pages) + page, return_index=True, return_counts=True)
    of, on = pair // len(pages), pair % len(pages)
    with np.errstate(over="ignore"):
        h = mix(keys.astype(np.int64).view(np.uint64)[on] + count.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    edge = np.searchsorted(of, np.arange(len(number)))
    with_it = np.bincount(of, minlength=len(number))
    lo = np.add.reduceat((h & np.uint64(0x7FFFFFFF)).astype(np.int64), edge)
    hi = np.add.reduceat((h >> np.uint64(33)).astype(np.int64), edge)
    # the page of least key that has the role, and the role's first place on it
    order = np.lexsort((on, keys[on], of))
    at = order[edge]
    place = first[at] - np.concatenate([[0], np.cumsum(size)])[on[at]]
    wide = np.flatnonzero(with_it >= least)
    if not len(wide):
        return []
    _, inv, twins = np.unique(np.stack([with_it[wide], lo[wide], hi[wide]]), axis=1, return_inverse=True, return_counts=True)
    names = list(number)
    return [(names[k], int(with_it[k]), int(lo[k]), int(hi[k]), int(keys[on[at[k]]]), int(place[k])) for k in wide[twins[inv.ravel()] >= MIN_CLASS].tolist()]


def _block(table: pa.Table) -> pa.Table:
    keys, n = table["key"].to_numpy(), table.num_rows
    alone = table["blocks"][0].as_py() == 1
    least = need(n) if alone else max(2, int(np.ceil(TENTH * n / 4)))
    rows = [(None, n, None, None, None, None)]
    if not alone or n >= MIN_PAGES:
        rows += block_roles(keys, [tokens(h)[0] for h in table["html"].to_pylist()], least)
    cols = list(zip(*rows))
    kinds = [pa.string(), *[pa.int64()] * 4, pa.int32()]
    return pa.table([pa.array([table["host"][0].as_py()] * len(rows)), *[pa.array(c, t) for c, t in zip(cols, kinds)]], ["host", "role", "pages", "lo", "hi", "first_key", "place"])


def _host_classes(table: pa.Table) -> pa.Table:
    """The classes of a host, most widespread first, as JSON lists of roles in their order on the page of least key."""
    pdf = pd.DataFrame({c: pd.Series(table[c].to_pylist(), dtype=object) for c in table.column_names})
    n = int(pdf["pages"][pdf["role"].isna()].sum())
    told = pdf[pdf["role"].notna()].astype({"pages": "int64", "lo": "int64", "hi": "int64", "first_key": "int64", "place": "int64"}).sort_values(["role", "first_key"])
    by = told.groupby("role", sort=True).agg(pages=("pages", "sum"), lo=("lo", "sum"), hi=("hi", "sum"), first_key=("first_key", "first"), place=("place", "first")).reset_index()
    by = by[by["pages"] >= need(n)] if n >= MIN_PAGES else by.iloc[:0]
    found = [g.sort_values("place")["role"].tolist() for _, g in by.groupby(["pages", "lo", "hi", "first_key"]) if len(g) >= MIN_CLASS]
    pages = dict(zip(by["role"], by["pages"]))
    found.sort(key=lambda c: (-pages[c[0]], -len(c), c[0]))
    host = pdf["host"].iloc[0]
    return pa.table([pa.array([host] if found else [], pa.string()), pa.array([json.dumps(found)] if found else [], pa.string())], ["host", "classes"])


def violations(roles: list[str], where: dict[str, tuple[int, int]], sizes: list[int], out: set[tuple[int, int]]) -> None:
    """Adds (i, i) for a class out of order on a page, and (i, j) where a token of j stands inside a repetition of i."""
    following: dict[int, int] = {}
    inside: list[int] = []
    for r in roles:
        at = where.get(r)
        if at is None:
            continue
        c, i = at
        for g in inside:
            if g != c:
                out.add((g, c))
        if i != following.get(c, 0):
            out.add((c, c))
            continue
        i += 1
        if i == sizes[c]:
            i = 0
            if c in inside:
                inside.remove(c)
        elif i == 1:
            inside.append(c)
        following[c] = i
    out.update((c, c) for c in inside)


def _carry(pages: DataFrame, table: DataFrame, column: str, how: str) -> DataFrame:
    """Pages with their host's row of a small table: broadcast up to BROADCAST_BYTES, else joined by a shuffle."""
    size = table.agg(F.coalesce(F.sum(F.length(column)), F.lit(0))).first()[0]
    return pages.join(F.broadcast(table) if size <= BROADCAST_BYTES else table, "host", how)


def _report(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: dict[str, tuple[dict, list, set]] = {}
    for batch in batches:
        for host, html, classes in zip(*[batch.column(k).to_pylist() for k in range(3)]):
            if host not in seen:
                c = json.loads(classes)
                seen[host] = ({r: (k, i) for k, roles in enumerate(c) for i, r in enumerate(roles)}, [len(x) for x in c], set())
            violations(tokens(html)[0], *seen[host])
    rows = [(host, i, j) for host, (_, _, out) in seen.items() for i, j in sorted(out)]
    if rows:
        a, b, c = zip(*rows)
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b, pa.int32()), pa.array(c, pa.int32())], ["host", "i", "j"])


def valid(classes: list[list[str]], reported: set[tuple[int, int]]) -> list[str]:
    """The roles of the template: classes in order, but for those out of order and those that don't nest with one before."""
    kept: list[int] = []
    for k in range(len(classes)):
        if (k, k) not in reported and not any((k, o) in reported and (o, k) in reported for o in kept):
            kept.append(k)
    return [r for k in kept for r in classes[k]]


def _templates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = [json.dumps(valid(json.loads(c), {(x["i"], x["j"]) for x in r or ()})) for c, r in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["host", "template"])


def fill(roles: list[str], shown: list[str], template: frozenset[str]) -> list[tuple[str, int, str]]:
    """(slot, instance, value) of a page."""
    rows: list[tuple[str, int, str]] = []
    slot, value, seen = "", [], {}

    def close() -> None:
        if value:
            rows.append((slot, seen.get(slot, 0), " ".join(value)))
            seen[slot] = seen.get(slot, 0) + 1
            value.clear()

    for r, w in zip(roles, shown):
        if r in template:
            close()
            slot = r
        elif w:
            value.append(w)
        elif template and "|" not in r and "@" not in r:
            close()  # markup outside the template ends a value; the slot takes its place
            slot = r
    close()
    return rows


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known: dict[str | None, frozenset[str]] = {}
    for batch in batches:
        step = 256
        for lo in range(0, batch.num_rows, step):
            part = batch.slice(lo, step)
            host, html, template = (part.column(k).to_pylist() for k in (1, 2, 3))
            rows, owner = [], []
            for i in range(part.num_rows):
                if host[i] not in known:
                    known[host[i]] = frozenset(json.loads(template[i])) if template[i] else frozenset()
                got = fill(*tokens(html[i]), known[host[i]])
                rows += got
                owner += [i] * len(got)
            if rows:
                a, b, c = zip(*rows)
                take = pa.array(owner, pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0).take(take), part.column(1).take(take), pa.array(a), pa.array(b, pa.int32()), pa.array(c)], ["page_id", "host", "slot", "instance", "value"])


def extract_pages(pages: DataFrame, block_pages: int = BLOCK_PAGES) -> DataFrame:
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), host_of(F.col("url").cast("string")).alias("host"), F.col("html").cast("string").alias("html")).where("html is not null")
    size = rows.groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("html")).alias("b"))
    most = F.ceil(F.col("n") / min(LEAST_PAGES, block_pages))
    blocks = F.least(most, F.greatest(F.ceil(F.col("n") / block_pages), F.ceil(F.col("b") / BLOCK_BYTES))).cast("int")
    many = cut(size.select("host", blocks.alias("blocks")).where("blocks > 1"))
    placed = rows.join(F.broadcast(many) if many.count() <= BROADCAST_HOSTS else many, "host", "left").select("host", "html", F.xxhash64("page_id", "html").alias("key"), F.coalesce("blocks", F.lit(1)).alias("blocks"))
    told = placed.withColumn("block", F.pmod(F.xxhash64("key"), F.col("blocks"))).groupBy("host", "block").applyInArrow(_block, ROLES)
    classes = cut(told.groupBy("host").applyInArrow(_host_classes, "host string, classes string"))
    reported = _carry(rows, classes, "classes", "inner").select("host", "html", "classes").mapInArrow(_report, "host string, i int, j int").groupBy("host").agg(F.collect_set(F.struct("i", "j")).alias("reported"))
    template = cut(classes.join(reported, "host", "left").select("host", "classes", "reported").mapInArrow(_templates, "host string, template string"))
    return _carry(rows, template, "template", "left").select("page_id", "host", "html", "template").mapInArrow(_extract, RESULT)


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(load(spark, sf_dir, "pages"))
