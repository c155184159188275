"""Each operator against a brute-force version, on the given tables and on odd ones."""

import collections
import hashlib
import math
import re
import zlib
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from shadowpack.llm import license_scan, minhash, packing, repeats
from shadowpack.llm.ann import nearest
from shadowpack.llm.decontaminate import decontaminate
from shadowpack.llm.html_extract import INSIDE, extract_text, page_lines, shared_lines
from shadowpack.llm.kernels import split_words, word_hashes
from shadowpack.llm.license_scan import scan_documents, scan_licenses
from shadowpack.llm.minhash import near_duplicates
from shadowpack.llm.packing import cutting_stock, pack
from shadowpack.llm.quality import quality_scores
from shadowpack.llm.queries import QUERIES, tokenizer_path
from shadowpack.llm.sharding import longest_first, shard_by_size
from shadowpack.llm.substring_dedup import substring_dedup
from shadowpack.llm.suffix_dedup import suffix_dedup

SPACES = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
ALNUM_BYTES = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
DOCS = "doc_id long, text string, lang string, n_words long, size long, shard int, score double"


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def passage(seed, n=60):
    return " ".join(f"w{seed}x{i}" for i in range(n))


def odd_rows():
    """Null, empty and blank texts, copies, ties, a passage shared by many, a long text, odd characters."""
    common = passage(1)
    rows = [(0, None), (1, ""), (2, " \n\t"), (3, common), (4, common), (5, f"a b {common} c"), (6, f"{passage(2)} {common}"), (7, f"{passage(3, 40)} {passage(3, 40)}"), (8, "one"), (9, "one"), (10, "One")]
    rows += [(11, "é" * 900), (12, "x" * 5000), (13, "ab" * 700), (14, " ".join(["same"] * 200)), (15, passage(4, 20_000)), (16, "<|endoftext|> It's DON'T naïve ÀÉ ½ 12345 !!! \x0b a\x1cb"), (17, "İstanbul é ‍\U0001f600."), (18, "a.b,c'd 's 'sx x's.")]
    rows += [(100 + i, f"{passage(50 + i, 30)} {passage(9, 40)} {passage(70 + i, 5)}") for i in range(12)]
    return rows


def frame(spark, rows):
    return spark.createDataFrame([(i, t, None, 1, 2, 3, 0.5) for i, t in rows], DOCS)


def by_id(df):
    rows = df.collect()
    out = {r["doc_id"]: r for r in rows}
    assert len(out) == len(rows)
    return out


def repeated_words(texts, length):
    words = {k: SPACES.findall(t or "") for k, t in texts.items()}
    count = collections.Counter(tuple(w[i : i + length]) for w in words.values() for i in range(len(w) - length + 1))
    out = {}
    for k, w in words.items():
        gone = [False] * len(w)
        for i in range(len(w) - length + 1):
            if count[tuple(w[i : i + length])] > 1:
                gone[i : i + length] = [True] * length
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out[k] = (len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest(), kept)
    return out


def repeated_bytes(texts, length):
    raw = {k: (t or "").encode() for k, t in texts.items()}
    count = collections.Counter(b[i : i + length] for b in raw.values() for i in range(len(b) - length + 1))
    out = {}
    for k, b in raw.items():
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if count[b[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out[k] = (len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest(), kept)
    return out


@pytest.mark.parametrize("cell", [1500, 2])
def test_substring_dedup(spark, monkeypatch, cell):
    monkeypatch.setattr(repeats, "CELL_CONTEXTS", cell)
    rows = odd_rows()
    want = repeated_words(dict(rows), 35)
    for k, r in by_id(substring_dedup(frame(spark, rows))).items():
        assert (r["n_words"], r["n_removed"], r["kept_sha256"], r["kept_text"]) == want[k], k


@pytest.mark.parametrize("cell", [1500, 2])
def test_suffix_dedup(spark, monkeypatch, cell):
    monkeypatch.setattr(repeats, "CELL_CONTEXTS", cell)
    rows = odd_rows()
    want = repeated_bytes(dict(rows), 100)
    for k, r in by_id(suffix_dedup(frame(spark, rows), 100)).items():
        assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"], bytes(r["kept_bytes"])) == want[k], k


@pytest.mark.parametrize("name", ["op3_substring_dedup", "op10_suffix_dedup"])
def test_dedup_on_tables(spark, small, name):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = by_id(QUERIES[name](spark, small))
    if name.startswith("op3"):
        assert {k: (r["n_words"], r["n_removed"], r["kept_sha256"]) for k, r in got.items()} == {k: v[:3] for k, v in repeated_words(texts, 35).items()}
    else:
        assert {k: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for k, r in got.items()} == {k: v[:4] for k, v in repeated_bytes(texts, 400).items()}


def test_planted_passages_at_400_bytes(spark):
    """Both passages have 57 words. With the spaces around them, which the documents share too, one has 400
    bytes and is removed, the other has 399 and stays; n_bytes is the size of the input either way."""
    long, short = (" ".join(f"w{seed}y{i:03}" for i in range(57))[:size] for seed, size in ((1, 398), (2, 397)))
    assert len(long.split()) == len(short.split()) == 57
    rows = [(i, f"a{i} {long} {i}b") for i in range(5)] + [(10 + i, f"c{i} {short} {i}d") for i in range(5)]
    rows += [(20 + i, f"{passage(20 + i, 300)} {i}") for i in range(5)]
    got = by_id(suffix_dedup(frame(spark, rows)))
    for k, text in rows:
        gone, kept = (400, f"a{k}{k}b") if k < 5 else (0, text)
        assert (got[k]["n_bytes"], got[k]["n_removed"], got[k]["n_spans"], bytes(got[k]["kept_bytes"])) == (len(text), gone, int(gone > 0), kept.encode()), k


def test_repeated_and_null_ids(spark):
    rows = [(1, passage(1)), (1, passage(1)), (None, passage(2)), (None, "z"), (2, passage(2))]
    got = sorted((str(r["doc_id"]), r["n_words"], r["n_removed"]) for r in substring_dedup(frame(spark, rows)).collect())
    assert got == sorted([("1", 60, 60), ("1", 60, 60), ("None", 60, 60), ("None", 1, 0), ("2", 60, 60)])
    assert suffix_dedup(frame(spark, rows), 50).count() == 5
    assert near_duplicates(frame(spark, rows)).where("kept").count() == 3
    assert pack(frame(spark, rows), tokenizer_path()).agg(F.sum("length")).first()[0] > 0
    assert shard_by_size(frame(spark, rows), 3).count() == 5
    assert scan_documents(frame(spark, rows).withColumn("source", F.lit("s"))).count() == 5


def test_empty_tables(spark):
    docs = frame(spark, [])
    labels = spark.createDataFrame([], "doc_id long, quality int")
    benchmark = spark.createDataFrame([], "item_id long, text string")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    for df in (
        substring_dedup(docs), suffix_dedup(docs), near_duplicates(docs), pack(docs, tokenizer_path()), shard_by_size(docs), quality_scores(docs, labels), decontaminate(docs, benchmark),
        extract_text(pages), nearest(vectors), scan_documents(docs.withColumn("source", F.lit("s"))),
    ):
        assert df.count() == 0
    few = frame(spark, odd_rows()[:5])
    assert {r["score"] for r in quality_scores(few, labels).collect()} == {0.5}
    assert {r["n_hit"] for r in decontaminate(few, benchmark).collect()} == {0}


def test_sharding(spark, small):
    assert longest_first([(5, ("a",)), (4, ("b",)), (3, ("c",)), (3, ("d",)), (3, ("e",))], 2) == {("a",): 0, ("b",): 1, ("c",): 1, ("d",): 0, ("e",): 1}
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang").unionByName(frame(spark, [(k + 10**6, t) for k, t in odd_rows()]).select("doc_id", "text", "lang"))
    text = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    groups, slots, load = {}, collections.defaultdict(list), collections.Counter()
    for r in shard_by_size(docs, 7).collect():
        b = text[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(b) + 1, zlib.crc32(b), "bytes", None)
        assert groups.setdefault(b, r["shard"]) == r["shard"]
        slots[r["shard"]].append(r["slot"])
        load[r["shard"]] += r["size"]
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and sum(map(len, slots.values())) == len(text)
    largest_group = max(collections.Counter({b: sum(len(x.encode()) + 1 for x in text.values() if x.encode() == b) for b in groups}).values())
    assert max(load.values()) <= max(largest_group, 1.01 * sum(load.values()) / 7)


def test_license_scan(spark):
    files = spark.createDataFrame(
        [(1, "a/LICENSE", "Released under the MIT License.\n"), (2, "a/b/x.py", "print(1)"), (3, "a/b/y.py", "code\n# Licensed under the Apache License, Version 2.0.\n" + "more code here and there\n" * 9), (4, "c/z", "nothing"), (5, None, None), (6, "a/b/c/LICENSE", "Licensed under CC BY-NC 4.0."), (7, "a/b/c/d/e", "x"), (8, "top", "y")],
        "doc_id long, path string, text string",
    )
    got = by_id(scan_licenses(files))
    assert {k: (r["license"], r["origin"], r["from_directory"]) for k, r in got.items()} == {
        1: ("MIT", "own", None), 2: ("MIT", "inherited", "a"), 3: ("Apache-2.0", "own", None), 4: (None, "none", None), 5: (None, "none", None), 6: ("CC-BY-NC-4.0", "own", None), 7: ("CC-BY-NC-4.0", "inherited", "a/b/c"), 8: (None, "none", None),
    }


def test_license_query_finds_every_statement(spark, small):
    found = {r["doc_id"] for r in QUERIES["op2_license_scan"](spark, small).where("origin = 'own'").collect()}
    lines = {r["doc_id"] for r in spark.read.parquet(f"{small}/documents.parquet").where("lower(text) like '%licens%'").collect()}
    assert lines <= found


def test_license_texts_headers_and_statements_in_lines(spark):
    texts = {p.stem: p.read_text() for p in (Path(license_scan.__file__).parent / "licenses").glob("*.txt")}
    owner = "Copyright (c) 2019 Some Body and others\n\n"
    wrapped = {
        "Apache-2.0": '# Licensed under the Apache License, Version 2.0\n# (the "License"); you may not use this file except in\n# compliance with the License. You may obtain a copy of\n# the License at http://www.apache.org/licenses/LICENSE-2.0\n',
        "GPL-2.0": " * This program is free software; you can redistribute it\n * and/or modify it under the terms of the GNU General\n * Public License as published by the Free Software\n * Foundation; either version 2 of the License, or\n * (at your option) any later version.\n",
        "LGPL-2.1": "// This library is free software; you can redistribute it\n// and/or modify it under the terms of the GNU Lesser General Public\n// License as published by the Free Software Foundation; either\n// version 2.1 of the License, or (at your option) any later version.\n",
        "GPL-3.0": "# This work is licensed under the GNU\n# General Public License,\n# version 3.\n",
    }
    lines = {"MIT": ["MIT License", "# SPDX-License-Identifier: MIT", "The tool and all of its manuals are released under the MIT License, see the file beside this one for more."], "GPL": ["GNU GENERAL PUBLIC LICENSE"], "Apache-2.0": ["Apache License"], "BSD-3-Clause": ["code under the BSD 3-Clause licence, as ever"]}
    code = "\n" + "def f(x): return x + 1  # some more code here and there\n" * 30
    rows = [(name, f"{name}/text", owner + text) for name, text in texts.items()] + [(name, f"h{name}/x.c", text + code) for name, text in wrapped.items()]
    rows += [(name, f"l{k}{name}/x.py", code + text + code) for name, many in lines.items() for k, text in enumerate(many)]
    rows += [("MIT", "named/LICENSE.md", "MIT License" + code), (None, "named/a/b.py", "x"), (None, "MIT/a/b.py", "x"), (None, "p/q", "mit der license und the general public, version 3"), (None, "p/license_plate.py", "the driver license")]
    got = by_id(scan_licenses(spark.createDataFrame([(i, p, t) for i, (_, p, t) in enumerate(rows)], "doc_id long, path string, text string")))
    inherited = {"named/a/b.py": ("MIT", "named"), "MIT/a/b.py": ("MIT", "MIT")}
    for i, (name, path, _) in enumerate(rows):
        r = got[i]
        want = (*inherited[path], "inherited") if path in inherited else (name, None, "own" if name else "none")
        assert (r["license"], r["from_directory"], r["origin"]) == want, path


def plain_scan(files, templates):
    """Per file its (class, cosine, license) candidates and the bytes they cover, by TF-IDF cosines of plain Python:
    single lines against all templates, and every window of a template's length. Words share a weight by bucket."""
    texts = {i: lower(t).encode() for i, _, t in files}
    found = {i: [(m.start(), m.end(), m.group()) for m in ALNUM_BYTES.finditer(t)] for i, t in texts.items()}
    known = sorted({w for many in found.values() for _, _, w in many} | {w for t in templates.values() for w in ALNUM_BYTES.findall(lower(t).encode())})
    data = np.frombuffer(b" ".join(known), np.uint8)
    starts, ends, _ = split_words(data, np.array([0, data.size]), "alnum")
    bucket = dict(zip(known, (word_hashes(data, starts, ends) % np.uint64(license_scan.BUCKETS)).tolist(), strict=True))
    lines = {i: [(m.start(), m.end()) for m in re.finditer(rb"[^\r\n]*(?:[\r\n]|$)", t) if ALNUM_BYTES.search(m.group())] for i, t in texts.items()}
    df, n_lines = collections.Counter(bucket[w] for many in found.values() for _, _, w in many), sum(map(len, lines.values()))
    idf = {w: math.log(1 + (n_lines + 1) / (df[b] + 1)) for w, b in bucket.items()}

    def vector(words):
        v = {w: k * idf[w] for w, k in collections.Counter(words).items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        return {w: x / norm for w, x in v.items()}

    def cosine(words, unit):
        return sum(x * unit.get(w, 0.0) for w, x in vector(words).items())

    units = {name: (vector(ws), len(ws)) for name, t in templates.items() for ws in [ALNUM_BYTES.findall(lower(t).encode())]}
    out = {}
    for i, many in found.items():
        hits, covered, present = [], set(), {w for _, _, w in many}
        may = {name: u for name, u in units.items() if math.sqrt(sum(x * x for w, x in u[0].items() if w in present)) >= license_scan.LEAST_COSINE - 1e-9}
        for lo, hi in lines[i]:
            words = [w for a, _, w in many if lo <= a < hi] if may else []
            scores = {name: cosine(words, u[0]) for name, u in may.items()}
            best = max(scores.values(), default=0.0)
            if best >= license_scan.LEAST_COSINE:
                hits += [(2 if name == "Proprietary" else 1, c, name) for name, c in scores.items() if c >= best - 1e-9]
                covered |= set(range(lo, hi))
        for name, (unit, length) in may.items():
            long = length > license_scan.EXACT_WORDS
            size = min(length, len(many)) if long else length
            windows = [(cosine([w for _, _, w in many[k : k + size]], unit), k) for k in range(len(many) - size + 1)]
            windows = [x for x in windows if x[0] >= (license_scan.PASSAGE_COSINE if long else 1 - 1e-6)]
            for c, k in [max(windows, key=lambda x: (x[0], -x[1]))] if long and windows else windows:
                hits.append((0 if long else 2 if name == "Proprietary" else 1, c, name))
                covered |= set(range(many[k][0], many[k + size - 1][1]))
        out[i] = hits, len(covered), len(texts[i])
    return out


def test_license_scan_against_plain_cosines(spark, small):
    """The given documents and changed statements (words left out, added, wrapped, said twice), own and inherited."""
    rows = [(r["doc_id"], f"{r['source']}/{r['lang']}/{r['doc_id']}", r["text"]) for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    for k, (name, text) in enumerate(license_scan.TEMPLATES.items()):
        w, at = text.split(), 10**6 + 100 * k
        changed = [text, " ".join(w[1:]), " ".join(w[:-1]), " ".join(w[: len(w) // 2]), " ".join(w[: len(w) // 2]) + "\n# " + " ".join(w[len(w) // 2 :]), f"{text} see the notes of all others", f"code here\n{text} {text}\r\nmore", f"x {text.upper()}" + "\nplain words of no weight" * 9]
        rows += [(at + j, f"t{k}/d{j}/f", x) for j, x in enumerate(changed)] + [(at + 50 + j, f"t{k}/d{j}/sub/g", f"nothing {j}") for j in range(len(changed))]
    want = plain_scan(rows, license_scan.TEMPLATES)
    got = by_id(scan_licenses(spark.createDataFrame(rows, "doc_id long, path string, text string"), license_scan.TEMPLATES))
    giving = {}
    for i, path, _ in rows:
        hits, covered, size = want[i]
        r = got[i]
        assert (r["origin"] == "own") == bool(hits), (i, hits)
        if hits:
            rank = min(h[0] for h in hits)
            best = max(c for q, c, _ in hits if q == rank)
            assert r["cosine"] == pytest.approx(min(best, 1.0), abs=2e-6)
            assert r["license"] in {name for q, c, name in hits if q == rank and c >= best - 2e-6}
            if covered >= license_scan.FILE_SHARE * size:
                giving.setdefault(path.rpartition("/")[0], []).append((-r["cosine"], i, r["license"]))
    assert {r["origin"] for r in got.values()} == {"own", "inherited", "none"}
    for i, path, _ in rows:
        if not want[i][0]:
            above = ["/".join(path.split("/")[:n]) for n in range(path.count("/"), -1, -1)]
            near = next((d for d in above if d in giving), None)
            assert (got[i]["license"], got[i]["from_directory"]) == (min(giving[near])[2] if near is not None else None, near)


PAGE = """<!doctype html><html><head><title>t</title><style>p{}</style><script>var a="<p>no</p>";</script></head><body class="page">
<nav><a href=x>Home</a></nav><div id="cookie-notice">We use cookies</div><div class="sidebar">Side</div><main><article><h1>A &amp; B</h1><p>One   two<br>three<p>Caf&eacute; <b>bold</b> text
<div class="share-buttons">Share</div><ul><li>x<li>y</ul><section class="comments"><p>First!</p></section></article></main><form><label>Mail</label></form><footer>&copy; me</footer>"""


def test_page_text(spark):
    rows = [(1, "http://h/a/1", PAGE), (2, "http://h/a/2", PAGE.replace("One", "Two")), (3, None, None), (4, "http://h/b", ""), (5, "odd url", "plain &lt;text&gt;"), (6, "http://g/1", "<div>Menu</div><div>own one</div>"), (7, "http://g/2", "<div>Menu</div><div>own two</div>"), (8, "http://i/1", "<div>alone</div>")]
    df = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, text string").coalesce(1)
    got = {r["page_id"]: r for r in extract_text(df).collect()}
    assert got[1]["text"] == "A & B\nOne two three\nCafé bold text\nx\ny"
    assert got[2]["text"].split("\n")[1] == "Two two three"
    assert [got[k]["text"] for k in (3, 4, 5, 6, 7, 8)] == ["", "", "plain <text>", "own one", "own two", "alone"]
    assert all(r["n_chars"] == len(r["text"]) and r["url"] == dict((a, b) for a, b, _ in rows)[k] for k, r in got.items())
    assert shared_lines(list("abcbd"), list("abd")) in ({0, 1, 4}, {0, 3, 4})
    assert page_lines("<p>a<table><tr><td>b<td>c</table>d") == [("a", 1), ("b", 1), ("c", 1), ("d", 1)]


def test_attribute_names_are_whole():
    page = "<article><p>See <a href=\"/hidden-gems\" title='The hidden cost'>gems</a> and <a href=/p?id=share>more</a> or <a HREF=\"/p?id=share&role=dialog\">that</a></p><p title=\"class=menu\" data-role=\"dialog\" data-id=ad>kept</p><p ID = 'share'>not</p><p hidden>nor</p><p class=x aria-hidden=true>this</p></article>"
    assert [text for text, kind in page_lines(page) if kind == INSIDE] == ["See gems and more or that", "kept"]


def longest_common(one, two):
    table = [[0] * (len(two) + 1) for _ in range(len(one) + 1)]
    for i, x in enumerate(one):
        for j, y in enumerate(two):
            table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
    return table[-1][-1]


def test_shared_lines_are_a_longest_common_subsequence():
    import random
    import time

    rng = random.Random(3)
    for _ in range(500):
        letters = "abcdefgh"[: rng.choice((2, 3, 8))]
        one, two = ([rng.choice(letters) for _ in range(rng.randint(0, 40))] for _ in range(2))
        found, left = sorted(shared_lines(one, two)), iter(two)
        assert len(found) == longest_common(one, two) and all(one[i] in left for i in found)
    began = time.time()
    assert len(shared_lines(["a"] * 40_000, ["b"] + ["a"] * 40_000 + ["b"])) == 40_000
    assert len(shared_lines(["b", *["a"] * 40_000], [*["a"] * 40_000, "b"])) == 40_000
    assert time.time() - began < 20


@pytest.mark.parametrize("pages", [256, 3])
def test_pages_without_articles_lose_their_template(spark, monkeypatch, pages):
    from shadowpack.llm import html_extract

    monkeypatch.setattr(html_extract, "RANGE_PAGES", pages)
    rows, want = [], {}
    for host in range(3):
        for n in range(12):
            own = [f"own line {host} {n} {k}" for k in range(1 + n % 4)]
            rows.append((100 * host + n, f"http://h{host}.org/a/{n:02d}", "".join(f"<div>{x}</div>" for x in [f"Home of h{host}", *own[:1], "Menu", "Menu", *own[1:], f"About h{host}"])))
            want[100 * host + n] = "\n".join(own)
    rows.append((900, "http://h0.org/a/03x", rows[3][2]))  # a copy tells nothing of the template
    want[900] = want[3]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    for parts in (1, 7):
        assert {r["page_id"]: r["text"] for r in extract_text(df.repartition(parts)).collect()} == want


def test_equal_cosines_go_by_vec_id(spark):
    rows = [(0, [1.0, 0.0, 0.0], "x")] + [(i, [2.0 ** (i - 1)] * 2 + [0.0], "x") for i in range(1, 25)]
    for size in (128, 2):
        got = nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>, query string"), list_vectors=size).orderBy("rank").collect()
        assert [(r["rank"], r["vec_id"]) for r in got] == [(k, k) for k in range(1, 6)]


def test_pages_on_tables(spark, small):
    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{small}/pages.parquet").collect()}
    import html

    for r in QUERIES["op4_html_extract"](spark, small).collect():
        body = re.search(r"<article>(.*?)(</article>|<footer|$)", pages[r["page_id"]], re.S).group(1)
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", "", b.replace("<br>", " ")))).strip() for b in re.split(r"</?(?:p|h1|div)>", body)]
        assert r["text"] == "\n".join(b for b in blocks if b)


def test_nearest(spark, small):
    rng = np.random.default_rng(1)
    v = rng.standard_normal((400, 8))
    v[7] = v[150]
    v[200:260] = v[50]
    rows = [(i, v[i].tolist()) for i in range(400)] + [(1000, None), (1001, [0.0] * 8), (1002, [math.nan] * 8), (1003, [1.0]), (1004, [None] * 8), (1050, [math.inf] * 8)]
    df = spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<double>, key string")
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    hits = total = 0
    got = collections.defaultdict(dict)
    for r in nearest(df, list_vectors=40).collect():
        got[r["query_id"]][r["rank"]] = (r["vec_id"], r["score"])
    assert sorted(got) == list(range(0, 400, 50))
    for q, ranks in got.items():
        s = unit @ unit[q]
        s[q] = -9
        want = sorted(range(400), key=lambda i: (-round(s[i], 12), i))[:5]
        assert sorted(ranks) == [1, 2, 3, 4, 5]
        assert all(abs(score - s[i]) < 1e-12 for i, score in ranks.values())
        hits += len({i for i, _ in ranks.values()} & set(want))
        total += 5
        if q in (50, 200, 250):
            assert [ranks[k][0] for k in range(1, 6)] == want
    assert hits / total >= 0.9
    few = spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0, 1.0]), (2, [0.0, 1.0])], "vec_id long, embedding array<double>")
    assert [(r["rank"], r["vec_id"]) for r in nearest(few).orderBy("rank").collect()] == [(1, 1), (2, 2)]


def test_nearest_of_isolated_vectors_and_small_clusters(spark, monkeypatch):
    from shadowpack.llm import ann

    rng = np.random.default_rng(4)
    centers = rng.standard_normal((150, 24))
    v = np.concatenate([c + 1e-4 * rng.standard_normal((1 + i % 3, 24)) for i, c in enumerate(centers)])
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>")
    for least in (ann.LEAST_LISTS, 1):  # with 1, some lists hold too few and all vectors are compared
        monkeypatch.setattr(ann, "LEAST_LISTS", least)
        monkeypatch.setattr(ann, "reach", lambda *_: (0.2, least))
        got = collections.defaultdict(list)
        for r in nearest(df, every=7, list_vectors=2).orderBy("query_id", "rank").collect():
            got[r["query_id"]].append(r["vec_id"])
        assert sorted(got) == list(range(0, len(v), 7)) and all(len(x) == len(set(x)) == 5 for x in got.values())
    exact = sum(got[q] == [i for i in np.argsort(-(unit @ unit[q])).tolist() if i != q][:5] for q in got)
    assert exact >= 0.9 * len(got)


def test_nearest_recall_on_tables(spark, small):
    rows = spark.read.parquet(f"{small}/embeddings.parquet").collect()
    ids, v = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], dtype=float)
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    got = collections.defaultdict(set)
    for r in QUERIES["op5_nearest_vectors"](spark, small).collect():
        got[r["query_id"]].add(r["vec_id"])
    hits = 0
    for i in np.flatnonzero(ids % 50 == 0):
        s = unit @ unit[i]
        s[i] = -9
        hits += len(got[ids[i]] & set(ids[np.argsort(-s)[:5]].tolist()))
    assert hits / (5 * (ids % 50 == 0).sum()) >= 0.9


def contaminated(texts, items):
    index, lengths = collections.defaultdict(set), set()
    for k, t in items:
        w = ALNUM.findall(lower(t))
        n = min(13, len(w))
        if n:
            lengths.add(n)
            for i in range(len(w) - n + 1):
                index[tuple(w[i : i + n])].add(str(k))
    out = {}
    for k, t in texts.items():
        w = ALNUM.findall(lower(t))
        hit, found = [0] * len(w), set()
        for n in lengths:
            for i in range(len(w) - n + 1):
                if (key := tuple(w[i : i + n])) in index:
                    found |= index[key]
                    hit[i : i + n] = [1] * n
        h = sum(hit)
        out[k] = (len(w), h, len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), h > 0 and 20 * h >= len(w))
    return out


@pytest.mark.parametrize("block", [1 << 20, 600])
def test_decontaminate(spark, small, block):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()} | {k + 10**6: t for k, t in odd_rows()}
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()] + [(900, passage(9, 40)), (901, "ONE"), (902, "w1x3, w1x4"), (903, None), (904, "..."), (901, "same Same")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = contaminated(texts, items)
    for k, r in by_id(decontaminate(frame(spark, list(texts.items())), bench, block_bytes=block)).items():
        assert (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) == want[k], k


def test_quality(spark):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()}
    right = total = 0
    for r in QUERIES["op7_quality"](spark, "/root/testdata/sf0.01").collect():
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.3)
        if r["held_out"] and r["doc_id"] in labels:
            total += 1
            right += r["predicted"] == labels[r["doc_id"]]
    assert right / total >= 0.95


def test_quality_ignores_everything_but_the_text(spark, small):
    docs, labels = spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/labels.parquet")
    base = {k: r["score"] for k, r in by_id(quality_scores(docs, labels)).items()}
    other = docs.withColumn("lang", F.lit("xx")).withColumn("source", F.lit(None).cast("string")).withColumn("score", F.lit(1))
    flipped = labels.withColumn("quality", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    assert {k: r["score"] for k, r in by_id(quality_scores(other.repartition(3), flipped)).items()} == pytest.approx(base, abs=1e-6)


def shingles(text, width):
    w = SPACES.findall(lower(text))
    return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])


def components(texts, width):
    sets = {k: shingles(t, width) for k, t in texts.items()}
    parent = {k: k for k in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    keys = sorted(sets)
    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            s, t = sets[a], sets[b]
            if s and t and min(len(s), len(t)) >= 0.8 * max(len(s), len(t)) and 100 * len(s & t) >= 80 * len(s | t):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return {k: (len(sets[k]), find(k)) for k in sets}


def near_rows():
    """Exact copies, near copies at and around the threshold, and a chain whose ends are not alike."""
    base = [f"t{i}" for i in range(81)]
    rows = [(1000 + i, " ".join(base)) for i in range(20)]
    for i in range(30):
        words = list(base)
        for j in range(i % 9 + 1):
            words[(7 * j + i) % 81] = f"new{i}x{j}"
        rows.append((2000 + i, " ".join(words)))
    chain = [f"c{i}" for i in range(60)]
    for step in range(10):
        rows.append((3000 + step, " ".join(chain)))
        for j in range(3):
            chain[(6 * step + 2 * j) % 60] = f"z{step}{j}"
    return rows


@pytest.mark.parametrize(("width", "block"), [(2, 4000), (2, 3), (5, 4000)])
def test_near_duplicates(spark, small, monkeypatch, width, block):
    monkeypatch.setattr(minhash, "BLOCK_MEMBERS", block)
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()} | {k + 10**6: t for k, t in odd_rows()} | dict(near_rows())
    want = components(texts, width)
    for k, r in by_id(near_duplicates(frame(spark, list(texts.items())), width)).items():
        assert (r["n_shingles"], r["component_id"], r["kept"]) == (*want[k], want[k][1] == k), k


def token_ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    return {k: np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], dtype="<u4") for k, x in texts.items()}


def check_packing(rows, texts):
    ids = token_ids(texts)
    pieces, sequences = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        pieces[r["doc_id"]].append(r)
        sequences[r["sequence_id"]].append(r)
    for k, own in ids.items():
        at = 0
        for r in sorted(pieces[k], key=lambda r: r["start"]):
            assert (r["start"], r["doc_tokens"]) == (at, len(own)) and r["length"] > 0
            assert r["ids_crc32"] == zlib.crc32(own[at : at + r["length"]].tobytes()), k
            at += r["length"]
        assert at == len(own)
    padding = 0
    for rows_ in sequences.values():
        at = 0
        for r in sorted(rows_, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 4096
        padding += 4096 - at if at & (at - 1) else 0
    return padding, sum(map(len, ids.values()))


def test_packing(spark, small):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()} | {k + 10**6: t for k, t in odd_rows()}
    padding, total = check_packing(pack(frame(spark, list(texts.items())), tokenizer_path()).collect(), texts)
    assert padding <= 0.02 * total
    few = dict(odd_rows()[:4])
    check_packing(pack(frame(spark, list(few.items())), tokenizer_path()).collect(), few)


def test_cutting_stock_is_near_its_bound():
    rng = np.random.default_rng(3)
    sizes = np.arange(1, 65)
    demand = rng.integers(0, 400, 64)
    sizes, demand = sizes[demand > 0], demand[demand > 0]
    patterns, bound = cutting_stock(sizes, demand, 64)
    assert all((p @ sizes) <= 64 for p, _ in patterns)
    assert (sum(p * k for p, k in patterns) >= demand).all()
    assert bound - 1e-6 <= sum(k for _, k in patterns) <= bound + len(sizes)
    assert bound >= (sizes @ demand) / 64 - 1e-6


def test_word_cache_overflow(monkeypatch):
    from pathlib import Path

    from shadowpack.llm.kernels import column_bytes

    monkeypatch.setattr(packing, "CACHE_WORDS", 8)
    import pyarrow as pa

    texts = ["a b c d e f", "g h i j k l.", "a it's b <|endoftext|>"]
    cache = packing.WordCache(Path(tokenizer_path()).read_text())
    want = token_ids(dict(enumerate(texts)))
    for i, t in enumerate(texts):
        ids, bounds = cache.encode(*column_bytes(pa.array([t])))
        assert ids.tolist() == want[i][:-1].tolist() and bounds.tolist() == [0, ids.size]


def test_text_with_more_words_than_the_cache(monkeypatch):
    import pyarrow as pa

    from shadowpack.llm.kernels import column_bytes

    monkeypatch.setattr(packing, "CACHE_WORDS", 8)
    texts = ["a b", " ".join(f"n{i}." for i in range(45)) + " n3 n44.", "it's b"]
    cache = packing.WordCache(Path(tokenizer_path()).read_text())
    want = token_ids(dict(enumerate(texts)))
    ids, bounds = cache.encode(*column_bytes(pa.array(texts)))
    assert [ids[a:b].tolist() for a, b in zip(bounds[:-1], bounds[1:], strict=True)] == [want[i][:-1].tolist() for i in range(3)]


def test_suffix_array_and_common_prefixes():
    from shadowpack.llm.kernels import kasai, suffix_order

    rng = np.random.default_rng(5)
    text = np.append(rng.integers(1, 3, 300), 0).astype(np.int16)
    order, rank = suffix_order(text)
    raw = text.tolist()
    assert order.tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
    common = kasai(text, order, rank, np.array([0, 150]), np.array([150, 150]), 20)
    for p in range(300):
        q = order[rank[p] - 1] if rank[p] else None
        h = 0
        while q is not None and h < 20 and p + h < 301 and q + h < 301 and raw[p + h] == raw[q + h]:
            h += 1
        assert common[p] == h


@pytest.mark.parametrize("small", [10**6, 0])
def test_components(spark, monkeypatch, small):
    from shadowpack.llm import components as module
    from shadowpack.llm.components import connected_components

    monkeypatch.setattr(module, "SMALL_EDGES", small)

    rng = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (200, 2))] + [(1000 + i, 1001 + i) for i in range(40)] + [(5000, 5000 + i) for i in range(50)]
    parent = {x: x for e in edges for x in e}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        parent[y] = x
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: find(x) for e in edges if e[0] != e[1] for x in e}


def test_spans_are_read_in_a_fresh_worker(tmp_path):
    import subprocess
    import sys

    import pyarrow as pa

    # read from a stream, as a worker does: pa.array of Python values would load pyarrow.compute by itself
    batch = pa.RecordBatch.from_pylist([{"spans": None}, {"spans": [{"first": 3, "n": 2}]}])
    with pa.OSFile(str(tmp_path / "batch"), "wb") as out, pa.ipc.new_stream(out, batch.schema) as writer:
        writer.write_batch(batch)
    code = "import sys, pyarrow as pa; from shadowpack.llm.repeats import span_arrays; print([x.tolist() for x in span_arrays(pa.ipc.open_stream(pa.OSFile(sys.argv[1])).read_next_batch().column(0), 0, 2)])"
    said = subprocess.run([sys.executable, "-c", code, str(tmp_path / "batch")], cwd=Path(__file__).parents[2], capture_output=True, text=True)
    assert said.stdout.strip() == "[[1], [3], [2]]", said.stderr
