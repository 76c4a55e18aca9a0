"""AVI motion-JPEG and HTML templates: round trips, planted structure, edge cases."""

from __future__ import annotations

import numpy as np
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from seqgrid.llm import html_template as H
from seqgrid.llm import media as M


def picture(rng, h, w):
    p = rng.integers(0, 256, (h, w)).astype(float)
    for _ in range(3):
        p = (p + np.roll(p, 1, 0) + np.roll(p, 1, 1)) / 3
    return np.clip(p, 0, 255)


def test_jpeg_round_trip():
    rng = np.random.default_rng(1)
    for h, w, restart in ((8, 8, 0), (24, 40, 0), (17, 23, 0), (33, 16, 2), (16, 64, 1)):
        p = picture(rng, h, w)
        (q,) = M.decode_jpeg(M.encode_jpeg(p, restart))
        assert q.shape == (h, w) and np.abs(q - p).max() < 14 and np.abs(q - p).mean() < 3


def test_jpeg_with_tables_and_colour():
    """A frame of three components, the chroma at half size, carrying its own Huffman tables."""
    import struct

    rng = np.random.default_rng(2)
    grey = M.encode_jpeg(picture(rng, 16, 16))
    counts, values = M.DC_LUMA
    dht = bytes([0]) + bytes(counts) + bytes(values)
    seg = b"\xff\xc4" + struct.pack(">H", len(dht) + 2) + dht
    assert np.array_equal(M.decode_jpeg(grey)[0], M.decode_jpeg(grey[:2] + seg + grey[2:])[0])
    # 4:2:0: one MCU of four flat luma blocks and two chroma blocks, all coefficients 0: the planes are mid grey
    dc, ac = M.huffman_codes(*M.DC_LUMA), M.huffman_codes(*M.AC_LUMA)
    dcc, acc = M.huffman_codes(*M.DC_CHROMA), M.huffman_codes(*M.AC_CHROMA)
    bits = "".join(format(t[0][0], f"0{t[0][1]}b") for t in ([dc, ac] * 4 + [dcc, acc] * 2))
    bits += "1" * (-len(bits) % 8)
    q = b"\xff\xdb\x00\x43\x00" + bytes([8] * 64)
    sof = b"\xff\xc0" + struct.pack(">HBHHB", 17, 8, 16, 16, 3) + b"\x01\x22\x00\x02\x11\x00\x03\x11\x00"
    sos = b"\xff\xda\x00\x0c\x03\x01\x00\x02\x11\x03\x11\x00\x3f\x00"
    planes = M.decode_jpeg(b"\xff\xd8" + q + sof + sos + int(bits, 2).to_bytes(len(bits) // 8, "big") + b"\xff\xd9")
    assert [p.shape for p in planes] == [(16, 16), (8, 8), (8, 8)] and all((p == 128).all() for p in planes)


def test_planted_shots_with_and_without_index():
    rng = np.random.default_rng(3)
    for key in range(30):
        raw, starts = M.film(rng.normal(size=64) * 0.15, key)
        assert [c[1] for c in M.clip_rows(raw)] == starts
        _, _, _, frames = M.parse_avi(raw)
        bare = M.write_avi(frames, 25, 16, 16, index=False)
        rows = M.clip_rows(bare)
        assert [c[1] for c in rows] == starts and rows[-1][2] == len(frames) and rows[-1][4] == round(len(frames) / 25, 6)


def test_media_edges(spark):
    good, starts = M.film(np.ones(64) * 0.1, 4)
    _, _, _, frames = M.parse_avi(good)
    torn = M.write_avi([frames[0], b"\xff\xd8junk", *frames[2:]], 10, 16, 16)
    rows = [(1, None), (2, b""), (3, b"RIFF"), (4, good[:60]), (5, good), (5, good), (None, good), (6, torn), (7, good[: len(good) // 2]), (8, M.write_avi([], 10, 16, 16)), (9, M.write_avi([b"x"], 10, 16, 16))]
    df = spark.createDataFrame([(i, None if b is None else bytearray(b)) for i, b in rows], "media_id long, avi binary")
    got = M.clips(df.withColumn("clip", F.lit("x")).withColumn("error", F.lit(1))).collect()
    of = {}
    for r in got:
        of.setdefault(r.media_id, []).append(r)
    assert all(len(of[k]) == 1 and of[k][0].clip is None and of[k][0].error for k in (1, 2, 3, 4, 8, 9))
    assert len(of[5]) == 2 * len(starts) and len(of[None]) == len(starts)
    assert sum(r.bad_frames for r in of[6]) == 1 and M.clips(df.limit(0)).count() == 0
    assert M.media_table(spark.createDataFrame([(1, None), (2, []), (None, [0.5])], "vec_id long, embedding array<float>")).where("avi is not null").count() == 2


def test_query_finds_the_drawn_shots(spark, sf):
    rows = M.op8_media_clips(spark, sf).where("clip is not null").groupBy("media_id").agg(F.sort_array(F.collect_list("start_frame")).alias("s")).collect()
    v = pq.read_table(f"{sf}/embeddings.parquet").to_pandas()
    want = {int(i): M.film(e, int(i))[1] for i, e in zip(v.vec_id, v.embedding)}
    assert {r.media_id: r.s for r in rows} == want


# ---- templates ----


def page(title, items, body):
    lis = "".join(f"<li><a href='/{x}'>{x}</a></li>" for x in items)
    return f"<!DOCTYPE html><html><head><title>{title}</title><script>var a='<p>';</script></head><body><ul>{lis}</ul><div class=main><h1>{title}</h1><p>{body}</p></div><!-- c --><footer>All rights</footer></body></html>"


def brute_template(pages):
    """Roles of valid classes from count vectors over all pages, with positions, in plain Python."""
    n = len(pages)
    vec, at = {}, {}
    for i, p in enumerate(pages):
        for k, r in enumerate(p[0]):
            vec.setdefault(r, [0] * n)[i] += 1
            at.setdefault((r, i), []).append(k)
    groups = {}
    for r, v in vec.items():
        groups.setdefault(tuple(v), []).append(r)
    groups = [(v, g) for v, g in groups.items() if len(g) >= 2 and sum(x > 0 for x in v) >= H.need(n)] if n >= H.MIN_PAGES else []
    spans = {}
    kept = []
    for v, g in groups:
        first = next(i for i in range(n) if v[i])
        order = sorted(g, key=lambda r: at[r, first][0])
        reps, good = [], True
        for i in range(n):
            for q in range(v[i]):
                places = [at[r, i][q] for r in order]
                good &= places == sorted(places) and (q + 1 >= v[i] or places[-1] < at[order[0], i][q + 1])
                reps.append((i, places))
        if good:
            spans[tuple(order)] = reps
            kept.append((v, order))
    kept.sort(key=lambda x: (-sum(y > 0 for y in x[0]), -len(x[1]), x[1][0]))

    def breaks(a, b):  # a token of b inside a repetition of a
        return any(i == j and any(x[0] < y < x[-1] for y in z) for i, x in spans[tuple(a)] for j, z in spans[tuple(b)])

    out = []
    for _, g in kept:
        if not any(breaks(g, o) and breaks(o, g) for o in out):
            out.append(g)
    return frozenset(r for g in out for r in g)


def brute_rows(rows):
    """(page_id, host, slot, instance, value) of (page_id, host, html)."""
    out = []
    for host in {h for _, h, _ in rows}:
        mine = [(i, H.tokens(x)) for i, h, x in rows if h == host]
        template = brute_template([t for _, t in mine])
        out += [(i, host, *r) for i, t in mine for r in H.fill(*t, template)]
    return sorted(out, key=str)


def layouts(n):
    """Pages of two layouts, the second of one page in six."""
    out = []
    for i in range(n):
        words = " ".join(f"w{(i * 7 + k * k) % 23}" for k in range(12))
        if i % 6 == 5:
            out.append(f"<html><body><table><tr><td>Name</td><td>n{i}</td></tr><tr><td>Price</td><td>{words}</td></tr></table><footer>Shop terms</footer></body></html>")
        else:
            out.append(page(f"T{i}", [f"x{i}{k}" for k in range(i % 3)], words))
    return out


def test_template_and_slots(spark):
    pages = [page(f"title{i}", [f"n{i}{k}" for k in range(i % 3 + 1)], f"text{i} more{i}&amp;co{i}") for i in range(12)]
    got = H.extract_pages(spark.createDataFrame([(i, "http://a.example/x", p) for i, p in enumerate(pages)], "page_id long, url string, html string")).collect()
    for i in range(12):
        mine = [r for r in got if r.page_id == i]
        assert [r.value for r in mine] == [f"title{i}", *[f"n{i}{k}" for k in range(i % 3 + 1)], f"title{i}", f"text{i} more{i}&co{i}"]
        assert [r.instance for r in mine if "li/a" in r.slot] == list(range(i % 3 + 1))


def test_extraction_matches_brute_force(spark):
    """Small hosts, and a hot host of many blocks with a layout of few pages: the template is that of all pages."""
    rows = [(i, "hot.example", x) for i, x in enumerate(layouts(150))] + [(1000 + i, f"h{i % 4}.example", x) for i, x in enumerate(layouts(36))]
    df = spark.createDataFrame([(i, f"http://{h}/{i}", x) for i, h, x in rows], "page_id long, url string, html string")
    want = brute_rows(rows)
    for blocks in (16, 512):
        assert sorted((tuple(r) for r in H.extract_pages(df, blocks).collect()), key=str) == want
    assert any(s == "html/body/table/tr/td|Price" or s.startswith("html/body/table/tr/td") and v == "n5" for _, h, s, _, v in want if h == "hot.example")


def test_unordered_and_crossing_classes_are_reported():
    out = set()
    where = {"a": (0, 0), "b": (0, 1), "x": (1, 0), "y": (1, 1)}
    H.violations(list("axyb"), where, [2, 2], out)
    assert out == {(0, 1)}
    H.violations(list("axby"), where, [2, 2], out)
    assert out == {(0, 1), (1, 0)}
    H.violations(list("ba"), where, [2, 2], out)
    assert (0, 0) in out and H.valid([["a", "b"], ["x", "y"]], {(0, 1), (1, 0)}) == ["a", "b"]
    assert H.valid([["a", "b"], ["x", "y"]], {(0, 1), (0, 0)}) == ["x", "y"]


def test_html_edges(spark):
    many = [(100 + i, f"http://www.a.example/{i}", page(f"T{i}", [f"x{i}"], f"B{i}")) for i in range(8)]
    rows = many + [(1, "http://b.example/", None), (2, "http://b.example/", ""), (3, None, "<p>lone &#233;t&eacute; &#xD800;"), (4, "not a url", "plain words"), (5, "http://c.example/", "<b>" * 30_000 + "deep"), (6, "http://d.example", "<p>" + "long " * 50_000), (100, many[0][1], many[0][2]), (None, "http://e.example", "<i>no id</i>")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("h")).withColumn("slot", F.lit(1)).withColumn("block", F.lit(2))
    got = H.extract_pages(df).collect()
    of = {}
    for r in got:
        of.setdefault(r.page_id, []).append(r.value)
    assert 1 not in of and 2 not in of and of[3] == ["lone ét&eacute; &#xD800;"] and of[4] == ["plain words"] and of[5] == ["deep"]
    assert len(of[6][0].split()) == 50_000 and of[None] == ["no id"]
    assert sorted(of[100]) == sorted(["T0", "x0", "T0", "B0"] * 2) and of[103] == ["T3", "x3", "T3", "B3"]
    assert {r.host for r in got if r.page_id == 101} == {"a.example"}
    assert H.extract_pages(df.limit(0)).count() == 0
