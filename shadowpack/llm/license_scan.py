"""License scan: sparse TF-IDF cosine of single lines, of passages across lines (statements, file headers) and
of whole licence texts to templates, then inheritance from the nearest ancestor directory by path joins."""

from __future__ import annotations

from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ship_package, stage, unique_ids
from .kernels import chunks, column_bytes, lower_table, ranges, split_words, word_hashes

# Statements by which texts name their license.
TEMPLATES = {
    "MIT": "Released under the MIT License.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-2.0": "This work is licensed under the GNU General Public License, version 2.",
    "LGPL-3.0": "Licensed under the GNU Lesser General Public License, version 3.",
    "AGPL-3.0": "Licensed under the GNU Affero General Public License, version 3.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted under the BSD 3-Clause License.",
    "CC-BY-4.0": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC0-1.0": "To the extent possible under law, all copyright and related rights are waived under CC0 1.0.",
    "Proprietary": "Copyright. All rights reserved.",
}
# Names and statements that count wherever these very words stand next to each other.
STATEMENTS = {
    "MIT": ("MIT License", "MIT licensed", "license MIT"),
    "Apache-2.0": ("Apache License", "Apache License, Version 2.0", "Apache 2.0 License", "Apache Software License", "Apache License 2.0"),
    "GPL": ("GNU General Public License", "GNU GPL", "licensed under the GPL"),
    "GPL-3.0": ("GNU General Public License version 3", "GNU General Public License v3", "version 3 of the GNU General Public License", "GPLv3", "GPL v3", "GNU GPL version 3"),
    "GPL-2.0": ("GNU General Public License version 2", "GNU General Public License v2", "version 2 of the GNU General Public License", "GPLv2", "GPL v2", "GNU GPL version 2"),
    "LGPL": ("GNU Lesser General Public License", "GNU LGPL"),
    "LGPL-3.0": ("GNU Lesser General Public License version 3", "GNU Lesser General Public License v3", "version 3 of the GNU Lesser General Public License", "LGPLv3", "LGPL v3"),
    "LGPL-2.1": ("GNU Lesser General Public License version 2.1", "GNU Lesser General Public License v2.1", "version 2.1 of the GNU Lesser General Public License", "LGPLv2.1", "LGPL v2.1"),
    "AGPL-3.0": ("GNU Affero General Public License", "GNU Affero General Public License version 3", "GNU Affero General Public License v3", "version 3 of the GNU Affero General Public License", "AGPLv3", "AGPL v3"),
    "MPL-2.0": ("Mozilla Public License Version 2.0", "Mozilla Public License v. 2.0", "Mozilla Public License 2.0", "MPL 2.0"),
    "BSD-2-Clause": ("BSD 2-Clause License", "2-Clause BSD License", "Simplified BSD License"),
    "BSD-3-Clause": ("BSD 3-Clause License", "3-Clause BSD License", "New BSD License", "Modified BSD License"),
    "ISC": ("ISC License", "license ISC"),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
    "CC-BY-4.0": ("CC BY 4.0", "Creative Commons Attribution 4.0"),
    "CC-BY-SA-4.0": ("CC BY-SA 4.0", "Creative Commons Attribution-ShareAlike 4.0"),
    "CC-BY-NC-4.0": ("CC BY-NC 4.0", "Creative Commons Attribution-NonCommercial 4.0"),
    "CC-BY-NC-SA-4.0": ("CC BY-NC-SA 4.0", "Creative Commons Attribution-NonCommercial-ShareAlike 4.0"),
    "CC-BY-ND-4.0": ("CC BY-ND 4.0", "Creative Commons Attribution-NoDerivatives 4.0"),
    "CC-BY-NC-ND-4.0": ("CC BY-NC-ND 4.0", "Creative Commons Attribution-NonCommercial-NoDerivatives 4.0"),
    "CC0-1.0": ("CC0 1.0", "Creative Commons Zero"),
    "Proprietary": ("All rights reserved.",),
}
# Headers of source files.
GNU_HEADER = "This {0} is free software{1} you can redistribute it and/or modify it under the terms of the GNU {2}General Public License as published by the Free Software Foundation{1} either version {3} of the License, or (at your option) any later version."
HEADERS = {
    "Apache-2.0": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0',
    "GPL-3.0": GNU_HEADER.format("program", ":", "", "3"),
    "GPL-2.0": GNU_HEADER.format("program", ";", "", "2"),
    "LGPL-3.0": GNU_HEADER.format("library", ";", "Lesser ", "3"),
    "LGPL-2.1": GNU_HEADER.format("library", ";", "Lesser ", "2.1"),
    "AGPL-3.0": GNU_HEADER.format("program", ":", "Affero ", "3"),
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
}
# What GNU's Affero text has in place of section 13 of its General Public License.
REMOTE = "Notwithstanding any other provision of this License, if you modify the Program, your modified version must prominently offer all users interacting with it remotely through a computer network an opportunity to receive the Corresponding Source of your version by providing access to the Corresponding Source from a network server at no charge."
# End of fixed values.

#: Passages of up to so many words must be there word for word; longer ones at this cosine.
EXACT_WORDS, PASSAGE_COSINE = 14, 0.8
#: File names of licence files.
LICENSE_FILE = r"(?i)(^|/)(un)?(licen[sc]e|copying)([-_][^/.]*)?(\.(txt|md|rst|html?|lesser|[0-9]+))?$"
#: Buckets of hashed words whose document frequencies are counted; least cosine of a match.
BUCKETS, LEAST_COSINE = 1 << 14, 0.72
#: A document is the licence file of its directory if matching lines hold this share of its bytes.
FILE_SHARE = 0.5


def line_words(data: np.ndarray, offsets: np.ndarray):
    """Lines of all rows as (row, first word, words), all words' hashes and places. Words: runs of letters,
    digits and non-ASCII characters, A-Z lower-cased."""
    lowered = lower_table()[data]
    breaks = np.flatnonzero((lowered == 0x0A) | (lowered == 0x0D)) + 1
    edges = np.unique(np.concatenate([offsets, breaks]))
    starts, ends, bounds = split_words(lowered, edges, "alnum")
    count = np.diff(bounds)
    keep = np.flatnonzero(count)
    row = np.searchsorted(offsets, edges[:-1][keep], side="right") - 1
    return row, bounds[:-1][keep], count[keep], edges[:-1][keep], edges[1:][keep], word_hashes(lowered, starts, ends), (starts, ends)


def frequency_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Lines that hold a word of each bucket (a word twice in a line counts twice), within the task."""
    df, lines = np.zeros(BUCKETS, dtype=np.int64), 0
    for batch in batches:
        data, offsets = column_bytes(batch.column(0))
        for a, b in chunks(offsets):
            _, _, count, _, _, words, _ = line_words(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            df += np.bincount((words % np.uint64(BUCKETS)).astype(np.int64), minlength=BUCKETS)
            lines += count.size
    if lines:
        yield pa.RecordBatch.from_arrays([pa.array(np.append(np.arange(BUCKETS), -1)), pa.array(np.append(df, lines))], ["bucket", "n"])


class Templates:
    """Unit TF-IDF vectors of the templates, as a sorted sparse table word -> weights."""

    def __init__(self, templates: dict[str, str], idf: np.ndarray):
        self.names, self.idf = list(templates), idf
        data, offsets = column_bytes(pa.array(list(templates.values())))
        lowered = lower_table()[data]
        starts, ends, bounds = split_words(lowered, offsets, "alnum")
        words, row = word_hashes(lowered, starts, ends), np.repeat(np.arange(len(templates)), np.diff(bounds))
        self.words = np.unique(words)
        self.weights = np.zeros((self.words.size, len(templates)), dtype=np.float64)
        np.add.at(self.weights, (np.searchsorted(self.words, words), row), 1.0)
        self.weights *= idf[(self.words % np.uint64(BUCKETS)).astype(np.int64)][:, None]
        self.weights /= np.maximum(np.linalg.norm(self.weights, axis=0), 1e-12)

    def best(self, words: np.ndarray, first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each line its best template (the first if equal) and the cosine."""
        line = np.repeat(np.arange(first.size), count)
        w = words[ranges(first, count)]
        known = self.words[np.minimum(np.searchsorted(self.words, w), self.words.size - 1)] == w
        score = np.zeros((first.size, len(self.names)))
        np.add.at(score, line[known], self.weights[np.searchsorted(self.words, w[known])] * self.idf[(w[known] % np.uint64(BUCKETS)).astype(np.int64)][:, None])
        # norms only where a known word occurs: elsewhere the cosine is 0
        some = np.zeros(first.size, dtype=bool)
        some[line[known]] = True
        in_some = some[line]
        order = np.lexsort((w[in_some], line[in_some]))
        lw, ww = line[in_some][order], w[in_some][order]
        new = np.ones(lw.size, dtype=bool)
        new[1:] = (lw[1:] != lw[:-1]) | (ww[1:] != ww[:-1])
        head = np.flatnonzero(new)
        tf = np.diff(np.append(head, lw.size))
        square = np.zeros(first.size)
        np.add.at(square, lw[head], (tf * self.idf[(ww[head] % np.uint64(BUCKETS)).astype(np.int64)]) ** 2)
        score /= np.maximum(np.sqrt(square), 1e-12)[:, None]
        pick = score.argmax(axis=1)
        return pick, score[np.arange(first.size), pick]


def default_passages() -> list[tuple[str, str]]:
    """(license, words): statements in both spellings, licence tags, headers and full texts."""
    texts = {p.stem: p.read_text() for p in sorted((Path(__file__).parent / "licenses").glob("*.txt"))}
    texts["AGPL-3.0"] = texts["GPL-3.0"].replace("GNU General Public License", "GNU Affero General Public License").replace("GNU GENERAL PUBLIC LICENSE", "GNU AFFERO GENERAL PUBLIC LICENSE") + REMOTE
    short = [(name, x) for name, many in STATEMENTS.items() for x in many] + [(k, v) for k, v in TEMPLATES.items() if k != "Proprietary"]
    names = sorted({*STATEMENTS, *TEMPLATES, *texts, "MIT-0", "0BSD", "Zlib", "BSL-1.0", "EPL-2.0", "Artistic-2.0"} - {"Proprietary", "GPL", "LGPL"})
    short += [(name, f"SPDX-License-Identifier: {name}") for name in names] + [(name, f"license {name}") for name in names if any(c.isdigit() for c in name)]
    short += [(name, x.replace("License", "Licence").replace("license", "licence")) for name, x in short if "icense" in x and "SPDX" not in x]
    return list(dict.fromkeys(short + list(HEADERS.items()) + list(texts.items())))


class Passages:
    """Templates that are compared with windows of their own length over a document's words, whatever line
    these stand in. Long ones step by a sixteenth of their length; a shorter document is one window."""

    def __init__(self, passages: list[tuple[str, str]], idf: np.ndarray):
        self.names, self.idf = [name for name, _ in passages], idf
        data, offsets = column_bytes(pa.array([x for _, x in passages]))
        lowered = lower_table()[data]
        starts, ends, bounds = split_words(lowered, offsets, "alnum")
        words, self.length = word_hashes(lowered, starts, ends), np.diff(bounds)
        self.words = np.unique(words)
        self.weights = np.zeros((self.words.size, len(passages)))
        np.add.at(self.weights, (np.searchsorted(self.words, words), np.repeat(np.arange(len(passages)), self.length)), 1.0)
        self.weights *= idf[(self.words % np.uint64(BUCKETS)).astype(np.int64)][:, None]
        self.weights /= np.maximum(np.linalg.norm(self.weights, axis=0), 1e-12)
        self.long = self.length > EXACT_WORDS
        self.least = np.where(self.long, PASSAGE_COSINE, 1 - 1e-6)
        self.square = (self.weights**2).astype(np.float32)

    def find(self, words: np.ndarray, bounds: np.ndarray) -> list[tuple[int, int, int, int, float]]:
        """(row, first word, end, passage, cosine) of the windows that match: all of short passages, the best of
        long ones. A row is looked into only for passages whose words it has: those present bound the cosine."""
        if not words.size:
            return []
        at = np.minimum(np.searchsorted(self.words, words), self.words.size - 1)
        known = self.words[at] == words
        row = np.repeat(np.arange(bounds.size - 1), np.diff(bounds))[known]
        if not row.size:
            return []
        pair_row, pair_word = np.divmod(np.unique(row * self.words.size + at[known]), self.words.size)
        heads = np.flatnonzero(np.diff(pair_row, prepend=-1))
        present = np.add.reduceat(self.square[pair_word], heads, axis=0)
        out = []
        weight = self.idf[(words % np.uint64(BUCKETS)).astype(np.int64)]
        for k, t in zip(*(x.tolist() for x in np.nonzero(present >= self.least**2 - 1e-3)), strict=True):
            r = int(pair_row[heads[k]])
            a, b = int(bounds[r]), int(bounds[r + 1])
            out += [(r, a + i, a + j, t, c) for i, j, c in self.windows(words[a:b], weight[a:b], np.where(known[a:b], self.weights[at[a:b], t], 0.0), t)]
        return out

    def windows(self, words: np.ndarray, idf: np.ndarray, own: np.ndarray, t: int) -> list[tuple[int, int, float]]:
        n, length, least = words.size, int(self.length[t]), self.least[t]
        if n < length and not self.long[t]:
            return []
        length = min(n, length)
        starts = np.unique(np.append(np.arange(0, n - length + 1, max(1, length // 16) if self.long[t] else 1), n - length))
        dot = np.concatenate([[0], np.cumsum(own * idf)])
        dot = dot[starts + length] - dot[starts]
        # squares of single occurrences: at most the window's norm, so at least its cosine
        low = np.concatenate([[0], np.cumsum(idf**2)])
        low = low[starts + length] - low[starts]
        may = np.flatnonzero(dot >= (least - 1e-6) * np.sqrt(low))
        starts, dot = starts[may], dot[may]
        cosine = np.zeros(starts.size)
        step = max(1, (1 << 20) // length)
        for a in range(0, starts.size, step):
            some = np.sort(words[starts[a : a + step, None] + np.arange(length)], axis=1)
            new = np.ones(some.shape, dtype=bool)
            new[:, 1:] = some[:, 1:] != some[:, :-1]
            head = np.flatnonzero(new)
            tf = np.diff(np.append(head, some.size))
            each = (tf * self.idf[(some.ravel()[head] % np.uint64(BUCKETS)).astype(np.int64)]) ** 2
            cosine[a : a + step] = dot[a : a + step] / np.sqrt(np.add.reduceat(each, np.flatnonzero(head % length == 0)))
        hit = np.flatnonzero(cosine >= least)
        if self.long[t] and hit.size:
            hit = hit[[int(np.argmax(cosine[hit]))]]
        return [(int(starts[i]), int(starts[i]) + length, min(1.0, float(cosine[i]))) for i in hit]


def match_kernel(shared, least: float):
    """Per document: its license and cosine, and the bytes of all matching lines and passages. Headers and full
    texts count before statements, a reserved right last; then the best cosine, the earliest, the longest."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        templates, passages = shared.value
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                here = offsets[a : b + 1] - offsets[a]
                row, first, count, start, end, words, place = line_words(data[offsets[a] : offsets[b]], here)
                n = b - a
                name: list[str | None] = [None] * n
                cosine, covered = np.zeros(n), np.zeros(n, dtype=np.int64)
                if row.size:
                    pick, score = templates.best(words, first, count)
                    hit = np.flatnonzero(score >= least)
                    found = [(int(row[k]), templates.names[pick[k]], False, float(score[k]), int(start[k]), int(end[k]), int(count[k])) for k in hit]
                    bounds = np.searchsorted(place[0], here)
                    found += [(r, passages.names[t], bool(passages.long[t]), c, int(place[0][i]), int(place[1][j - 1]), j - i) for r, i, j, t, c in passages.find(words, bounds)]
                    best: dict = {}
                    edge = np.zeros(here[-1] + 1, dtype=np.int64)
                    for r, licence, is_long, c, lo, hi, size in found:
                        key = (0 if is_long else 2 if licence == "Proprietary" else 1, -round(c, 6), lo, -size)
                        if r not in best or key < best[r][0]:
                            best[r] = (key, licence, c)
                        edge[lo] += 1
                        edge[hi] -= 1
                    for r, (_, licence, c) in best.items():
                        name[r], cosine[r] = licence, c
                    if best:
                        inside = np.concatenate([[0], np.cumsum(np.cumsum(edge[:-1]) > 0)])
                        covered = inside[here[1:]] - inside[here[:-1]]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, n), pa.array(np.diff(offsets[a : b + 1])), pa.array(name, pa.string()), pa.array(cosine), pa.array(covered)], ["_uid", "n_bytes", "license", "cosine", "covered"])

    return kernel


def scan_licenses(files: DataFrame, templates: dict[str, str] | None = None, least: float = LEAST_COSINE, file_share: float = FILE_SHARE) -> DataFrame:
    """License of every file: its own, if a line's TF-IDF cosine to a template reaches `least`, or if a statement,
    a file header or a licence's text stands in it, over any lines (Passages; with `templates` given, these
    alone); else that of the nearest ancestor directory with a licence file.

    files: doc_id, path ('/'-separated), text; other columns are ignored. A licence file is one whose
    matching lines and passages hold at least file_share of its bytes, or one with a license of its own and
    the name of a licence file (LICENSE, COPYING, UNLICENSE and the like); of several in a directory, that of the
    highest cosine counts (ties: the smallest doc_id). Word weights come from the frequencies of hashed words
    over all lines of all files. Returns doc_id, path, license (null if none), cosine (0 if not its own),
    origin ('own', 'inherited', 'none'), from_directory (of an inherited one). One row per input row.
    Null texts and paths count as empty; a path without '/' lies in the directory ''. Empty table: empty
    result. Rows with a null or repeated doc_id count as files of their own."""
    spark = files.sparkSession
    ship_package(spark)
    ids = unique_ids(files.select("doc_id", F.coalesce("path", F.lit("")).alias("path"), "text"))
    counted = ids.select("text").mapInArrow(frequency_kernel, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).collect()
    df, lines = np.zeros(BUCKETS), 1
    for r in counted:
        if r["bucket"] >= 0:
            df[r["bucket"]] = r["n"]
        else:
            lines = r["n"]
    idf = np.log(1 + (lines + 1) / (df + 1))
    passages = Passages(list(templates.items()) if templates else default_passages(), idf)
    shared = spark.sparkContext.broadcast((Templates(templates or TEMPLATES, idf), passages))
    own = ids.select("_uid", "text").mapInArrow(match_kernel(shared, least), "_uid long, n_bytes long, license string, cosine double, covered long")
    paths = ids.select("_uid", "doc_id", "path", F.regexp_extract("path", r"^(.*)/[^/]*$", 1).alias("directory"))
    rows = stage(own.join(paths, "_uid"), "licenses")
    better = F.row_number().over(Window.partitionBy("directory").orderBy(F.desc("cosine"), "_uid"))
    is_file = (F.col("covered") >= file_share * F.col("n_bytes")) | F.col("path").rlike(LICENSE_FILE)
    marked = rows.where(is_file & F.col("license").isNotNull())
    marked = marked.withColumn("nth", better).where("nth = 1").select(F.col("directory").alias("ancestor"), F.col("license").alias("given"))
    # each directory once: its ancestors, nearest first, joined to directories with a licence file
    steps = F.split("directory", "/")
    ancestors = F.transform(F.sequence(F.size(steps), F.lit(0), F.lit(-1)), lambda k: F.concat_ws("/", F.slice(steps, F.lit(1), k)))
    above = rows.select("directory").distinct().select("directory", F.posexplode(F.array_distinct(ancestors)).alias("depth", "ancestor"))
    nearest = above.join(marked, "ancestor").groupBy("directory").agg(F.min(F.struct("depth", "given", "ancestor")).alias("m")).select("directory", "m.given", "m.ancestor")
    joined = rows.where("license is null").join(nearest, "directory", "left")
    kept = rows.where("license is not null").select("doc_id", "path", "license", "cosine", F.lit("own").alias("origin"), F.lit(None).cast("string").alias("from_directory"))
    return kept.unionByName(joined.select("doc_id", "path", F.col("given").alias("license"), F.lit(0.0).alias("cosine"), F.when(F.col("given").isNull(), "none").otherwise("inherited").alias("origin"), F.col("ancestor").alias("from_directory")))


def scan_documents(docs: DataFrame, **options) -> DataFrame:
    """scan_licenses over a table without paths: a document's path is source/lang/doc_id, so a document that
    is little but a license statement stands for the documents of its source and language."""
    path = F.concat_ws("/", F.coalesce("source", F.lit("")), F.coalesce("lang", F.lit("")), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    return scan_licenses(docs.select("doc_id", path.alias("path"), "text"), **options)
