"""License scans: sparse TF-IDF cosine to templates, then inheritance from the nearest ancestor directory.

The templates are whole license texts (`licence_texts/`), the opening lines of each, standard notices, one-line notices
by name, and SPDX tags.  A licence file is compared whole first, and a full text it agrees with is its license.
Otherwise, and for all other files, the candidate texts are the header, comment blocks and runs of lines that speak of a
licence, each such line by itself, and each license an SPDX tag names.  A candidate is a sparse vector of words and word
pairs, weighted by inverse document frequency over the templates, and compared with every template; the best one at or
above `threshold` is the file's own license.  A directory has the license of its licence files; a file without a
license of its own takes that of its nearest ancestor directory, found by joining its ancestor paths with those.

The templates are a fixed list, so their vectors travel with the task; no corpus data is broadcast.  Ancestor rows are
one per directory level of a path; directories are distinct before the join.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from functools import cache
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialize
from .common import arrow_map, batches, held_by, table

#: Standard notices, by SPDX identifier.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
        "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION",
    ),
    "MIT": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction.",
    ),
    "GPL-2.0": ("This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License version 2.",),
    "BSD-3-Clause": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products.",),
    "MPL-2.0": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    ),
    "EPL-2.0": (
        "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
        "Eclipse Public License - v 2.0 THE ACCOMPANYING PROGRAM IS PROVIDED UNDER THE TERMS OF THIS ECLIPSE PUBLIC LICENSE (AGREEMENT). ANY USE, REPRODUCTION OR DISTRIBUTION OF THE PROGRAM CONSTITUTES RECIPIENT'S ACCEPTANCE OF THIS AGREEMENT. 1. DEFINITIONS",
        "Eclipse Public License - v 2.0 THE ACCOMPANYING PROGRAM IS PROVIDED UNDER THE TERMS OF THIS ECLIPSE PUBLIC LICENSE (AGREEMENT). ANY USE, REPRODUCTION OR DISTRIBUTION OF THE PROGRAM CONSTITUTES RECIPIENT'S ACCEPTANCE OF THIS AGREEMENT.",
    ),
    "EPL-1.0": ("This program and the accompanying materials are made available under the terms of the Eclipse Public License v1.0 which accompanies this distribution, and is available at http://www.eclipse.org/legal/epl-v10.html",),
    "CC0-1.0": ("To the extent possible under law, the author has waived all copyright and related rights: CC0 1.0 Universal.", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
}
#: The families whose notices are made from GNU_NOTICE, by identifier: full name and version.
GNU = {
    "GPL-1.0": ("General", "1"), "GPL-2.0": ("General", "2"), "GPL-3.0": ("General", "3"), "AGPL-3.0": ("Affero General", "3"),
    "LGPL-2.0": ("Library General", "2"), "LGPL-2.1": ("Lesser General", "2.1"), "LGPL-3.0": ("Lesser General", "3"),
}
GNU_NOTICE = (
    "This {0} is free software: you can redistribute it and/or modify it under the terms of the GNU {1} Public License as published by the Free Software Foundation, either version {2} of the License",
    ", or (at your option) any later version.",
    " This {0} is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {1} Public License for more details.",
)
#: Names in one-line notices, by SPDX identifier; every identifier here has an SPDX tag too.
NAMES: dict[str, tuple[str, ...]] = {
    "Apache-2.0": ("Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 License", "Apache-2.0"),
    "MIT": ("MIT License", "MIT license (MIT)", "MIT"),
    "GPL-1.0": ("GNU General Public License, version 1", "GPLv1", "GPL-1.0"),
    "GPL-2.0": ("GNU General Public License, version 2", "GNU General Public License v2.0", "GNU GPL v2", "GPL v2", "GPLv2", "GPL-2.0"),
    "GPL-3.0": ("GNU General Public License, version 3", "GNU General Public License v3.0", "GNU GPL v3", "GPL v3", "GPLv3", "GPL-3.0"),
    "AGPL-3.0": ("GNU Affero General Public License, version 3", "GNU Affero General Public License v3.0", "GNU AGPL v3", "AGPL v3", "AGPLv3", "AGPL-3.0"),
    "LGPL-2.0": ("GNU Library General Public License, version 2", "LGPLv2", "LGPL-2.0"),
    "LGPL-2.1": ("GNU Lesser General Public License, version 2.1", "GNU Lesser General Public License v2.1", "LGPL v2.1", "LGPLv2.1", "LGPL-2.1"),
    "LGPL-3.0": ("GNU Lesser General Public License, version 3", "GNU Lesser General Public License v3.0", "GNU LGPL v3", "LGPL v3", "LGPLv3", "LGPL-3.0"),
    "BSD-2-Clause": ("BSD 2-Clause License", "2-Clause BSD License", "Simplified BSD License", "BSD-2-Clause"),
    "BSD-3-Clause": ("BSD 3-Clause License", "3-Clause BSD License", "New BSD License", "Modified BSD License", "BSD-3-Clause"),
    "ISC": ("ISC License", "ISC"),
    "Zlib": ("zlib License", "Zlib"),
    "Unlicense": ("Unlicense",),
    "BSL-1.0": ("Boost Software License, Version 1.0", "BSL-1.0"),
    "MPL-1.1": ("Mozilla Public License, Version 1.1", "MPL-1.1"),
    "MPL-2.0": ("Mozilla Public License, Version 2.0", "Mozilla Public License 2.0", "MPL 2.0", "MPL-2.0"),
    "EPL-1.0": ("Eclipse Public License, Version 1.0", "Eclipse Public License 1.0", "EPL-1.0"),
    "EPL-2.0": ("Eclipse Public License, Version 2.0", "Eclipse Public License 2.0", "Eclipse Public License - v 2.0", "EPL-2.0"),
    "Artistic-1.0": ("Artistic License, Version 1.0", "Artistic-1.0"),
    "Artistic-2.0": ("Artistic License, Version 2.0", "Artistic License 2.0", "Artistic-2.0"),
    "GFDL-1.2": ("GNU Free Documentation License, Version 1.2", "GFDL-1.2"),
    "GFDL-1.3": ("GNU Free Documentation License, Version 1.3", "GFDL-1.3"),
    "CC0-1.0": ("Creative Commons CC0 1.0 Universal", "CC0 1.0 Universal", "CC0 1.0", "CC0-1.0"),
} | {
    f"CC-{code}-{v}": (f"CC {code} {v}", f"CC-{code}-{v}", f"Creative Commons {name} {v} International License", f"Creative Commons {name} {v} License")
    for code, name in (
        ("BY", "Attribution"), ("BY-SA", "Attribution-ShareAlike"), ("BY-NC", "Attribution-NonCommercial"), ("BY-ND", "Attribution-NoDerivatives"),
        ("BY-NC-SA", "Attribution-NonCommercial-ShareAlike"), ("BY-NC-ND", "Attribution-NonCommercial-NoDerivatives"),
    )
    for v in ("2.0", "2.5", "3.0", "4.0")
}
#: How a one-line notice is worded.
WORDINGS = ("Licensed under {}.", "Licensed under the {}.", "Released under the {}.", "This work is licensed under a {}.", "This work is licensed under the {}.", "This project is licensed under the {}.", "Distributed under the {}.", "License: {}")
#: A candidate of this many words or more can be a whole license; lines of the opening templates of each.
FULL_WORDS, OPENINGS = 80, (2, 4, 10)
#: From this cosine on, the whole text of a licence file decides alone.
WHOLE = 0.9
TEXTS = Path(__file__).resolve().parent / "licence_texts"
#: A line with one of these is a candidate wherever it stands.
MARKERS = re.compile(r"licen[sc]e|copyright|spdx|redistribut|permission is hereby|public domain|cc by|cc0|creative commons", re.IGNORECASE)
#: Names of licence files.
LICENSE_NAME = r"(?i)(^|/)(licen[sc]e|copying|copyright|notice|unlicense)(\.(txt|md|rst))?$"
HEADER_LINES = 10
THRESHOLD = 0.72
WORD = re.compile(r"[a-z0-9]+(?:[.-][a-z0-9]+)*")
SPDX = re.compile(r"SPDX-License-Identifier:\s*([^\n]*)", re.IGNORECASE)
SPDX_ID = re.compile(r"[A-Za-z0-9][A-Za-z0-9.+-]*")
COMMENT = re.compile(r"\s*(?://|/\*|\*|#|--|;|%|<!--|\.\.|REM\b|dnl\b)", re.IGNORECASE)


@held_by(__name__)
@cache
def standard() -> dict[str, tuple[str, ...]]:
    """All templates: notices, one-line notices, SPDX tags, opening lines and whole texts.  Read by the driver alone."""
    out: dict[str, list[str]] = {k: list(v) for k, v in TEMPLATES.items()}
    for k, names in NAMES.items():
        tags = [k, *(f"{k}{end}" for end in ("-only", "-or-later", "+") if "GPL" in k or "GFDL" in k)]
        out.setdefault(k, []).extend([w.format(n) for n in names for w in WORDINGS] + [f"SPDX-License-Identifier: {t}" for t in tags])
    for k, (family, version) in GNU.items():
        notices = ("".join(GNU_NOTICE[:n]).format(what, family, version) for what in ("program", "library") for n in (1, 2, 3))
        out.setdefault(k, []).extend(notices)
    for f in sorted(TEXTS.glob("*.txt")):
        text = f.read_text("utf-8")
        lines = [x for x in text.split("\n") if x.strip()]
        k = f.stem.removesuffix("-Regents")
        out.setdefault(k, []).extend(["\n".join(lines[:n]) for n in OPENINGS if len(lines) > n and len(lines) > 60] + [text])
    return {k: tuple(dict.fromkeys(v)) for k, v in out.items()}


def terms(text: str) -> Counter:
    """Words and neighbouring word pairs."""
    w = WORD.findall(text.lower())
    return Counter(w) + Counter(f"{a} {b}" for a, b in zip(w, w[1:], strict=False))


class Templates:
    """Unit TF-IDF vectors of the templates, as postings."""

    def __init__(self, templates: dict[str, tuple[str, ...]]) -> None:
        bags = [(k, terms(t)) for k, ts in templates.items() for t in ts]
        seen = Counter(t for _, b in bags for t in b)
        self.idf = {t: math.log((1 + len(bags)) / (1 + n)) + 1 for t, n in seen.items()}
        self.unknown = math.log(1 + len(bags)) + 1
        self.names = [k for k, _ in bags]
        self.full = [sum(n for t, n in b.items() if " " not in t) >= FULL_WORDS for _, b in bags]
        self.postings: dict[str, list[tuple[int, float]]] = {}
        for i, (_, b) in enumerate(bags):
            size = math.sqrt(sum((n * self.idf[t]) ** 2 for t, n in b.items()))
            for t, n in b.items():
                self.postings.setdefault(t, []).append((i, n * self.idf[t] / size))

    def best(self, text: str) -> tuple[str | None, float, bool]:
        """Most similar template, its cosine, and whether it is a whole license; ties go to the first in the list."""
        bag = terms(text)
        size = math.sqrt(sum((n * self.idf.get(t, self.unknown)) ** 2 for t, n in bag.items()))
        score = [0.0] * len(self.names)
        for t, n in bag.items():
            for i, w in self.postings.get(t, ()):
                score[i] += n * self.idf[t] * w
        if not size or not max(score):
            return None, 0.0, False
        i = max(range(len(score)), key=lambda k: (score[k], -k))
        return self.names[i], score[i] / size, self.full[i]


def candidates(text: str) -> list[str]:
    """Texts of a file that may state a license: marked lines and runs of them, SPDX tags, comment blocks, the header."""
    if not MARKERS.search(text):
        return []
    lines = text.split("\n")
    out, run, block = [], [], []
    for line in [*lines, ""]:
        if MARKERS.search(line):
            run.append(line)
            out.append(line)
        else:
            if len(run) > 1:
                out.append("\n".join(run))
            run = []
        if COMMENT.match(line):
            block.append(line)
        else:
            if len(block) > 1 and any(map(MARKERS.search, block)):
                out.append("\n".join(block))
            block = []
    out += [f"SPDX-License-Identifier: {x}" for found in SPDX.findall(text) for x in SPDX_ID.findall(found)]
    filled = [x for x in lines[: 4 * HEADER_LINES] if x.strip()]
    for header in ("\n".join(x) for x in (lines[:HEADER_LINES], *(filled[:n] for n in OPENINGS))):
        if MARKERS.search(header):
            out.append(header)
    return list(dict.fromkeys(out))


def own_licenses(files: DataFrame, threshold: float = THRESHOLD, templates: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """(doc_id, path, is_license_file, own_license, cosine) of every file (doc_id, path, text).

    Null text or path: empty.  A licence file whose whole text is a full license has that one; otherwise a file with
    several licenses gets the one with the highest cosine, ties by name.
    """
    known = templates or standard()

    def run(it):
        t = Templates(known)
        seen: dict[str, tuple[str | None, float, bool]] = {}
        for b in batches(it):
            names, scores = [], []
            for text, whole in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                best: tuple[float, str] | None = None
                all_ = t.best(text) if text and whole else (None, 0.0, False)
                if all_[0] and all_[1] >= threshold:
                    best = (-all_[1], all_[0])
                for c in candidates(text) if text and not (all_[2] and all_[1] >= max(threshold, WHOLE)) else []:
                    got = seen.get(c)
                    if got is None:
                        got = t.best(c)
                        if len(c) < 300 and len(seen) < 50_000:
                            seen[c] = got
                    if got[0] and got[1] >= threshold and (best is None or (-got[1], got[0]) < best):
                        best = (-got[1], got[0])
                names.append(best[1] if best else None)
                scores.append(-best[0] if best else 0.0)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), pa.array(names, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "path", "is_license_file", "own_license", "cosine"])

    path = F.coalesce(F.col("path").cast("string"), F.lit(""))
    src = files.select(F.col("doc_id").cast("long").alias("doc_id"), path.alias("path"), F.col("text").cast("string").alias("text"), path.rlike(LICENSE_NAME).alias("whole"))
    return arrow_map(src, run, "doc_id long, path string, is_license_file boolean, own_license string, cosine double")


def inherit(own: DataFrame) -> DataFrame:
    """doc_id, path, own_license, cosine, license, license_from of every row of own_licenses().

    license is the file's own, else that of the nearest ancestor directory with a licence file; license_from is `own`,
    the directory (`` for the root), or null with a null license.  A directory with several licence files takes the
    highest cosine, ties by path.
    """
    folder = F.regexp_replace("path", r"/?[^/]*$", "")
    best = F.min_by("own_license", F.struct(-F.col("cosine"), F.col("path")))
    dirs = own.filter("is_license_file AND own_license IS NOT NULL").groupBy(folder.alias("dir")).agg(best.alias("dir_license"))
    # Directories, not files, look for their ancestors: one row per level of each distinct directory.
    parts = F.split("dir", "/")
    levels = F.transform(F.sequence(F.lit(0), F.size(parts)), lambda i: F.array_join(F.slice(parts, 1, i), "/"))
    looking = own.filter("own_license IS NULL").select(folder.alias("dir")).distinct().select("dir", F.explode(F.array_distinct(levels)).alias("up"))
    near = looking.join(dirs.withColumnRenamed("dir", "up"), "up").groupBy("dir").agg(F.max_by(F.struct("up", "dir_license"), F.length("up")).alias("near"))
    out = own.withColumn("dir", folder).join(near, "dir", "left")
    return out.select(
        "doc_id", "path", "own_license", F.round("cosine", 6).alias("cosine"),
        F.coalesce("own_license", "near.dir_license").alias("license"),
        F.when(F.col("own_license").isNotNull(), F.lit("own")).otherwise(F.col("near.up")).alias("license_from"),
    )


def scan(files: DataFrame, **options) -> DataFrame:
    """License of every file (doc_id, path, text); see own_licenses() and inherit().

    Rows that repeat repeat the result, extra columns are dropped, an empty table gives no rows.
    """
    return inherit(materialize(own_licenses(files, **options), "licenses"))


def as_files(docs: DataFrame) -> DataFrame:
    """Paths for documents, which have none: source/shard/doc_id.txt, and source/shard/LICENSE for the short documents that
    end in a notice (no more than 60 words), as a repository would keep it."""
    words = F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), 0))
    notice = F.coalesce(F.element_at(F.split("text", "\n"), -1), F.lit("")).rlike("(?i)licen[sc]e")
    shard = F.concat_ws("/", F.coalesce("source", F.lit("none")), F.concat(F.lit("shard"), F.pmod(F.col("doc_id"), F.lit(97)).cast("string")))
    return docs.select("doc_id", F.concat_ws("/", shard, F.when(notice & (words <= 60), F.lit("LICENSE")).otherwise(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("none")), F.lit(".txt")))).alias("path"), "text")


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(as_files(table(spark, sf_dir, "documents")))
