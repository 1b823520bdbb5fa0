"""License scans by conditional compression.

A candidate block is every line round a licence's marker words that belongs to a wording: lines mostly made of runs
of four words of any template, over blank lines and up to ``gap`` other lines. Each block is compressed alone and
with every template as a raw zstandard dictionary; the templates are ranked by how much smaller the block becomes.
The best is confirmed by the exact wording: the words that the block has and a wording lacks, and the reverse.

Defined results: a null or empty text has no block; a block that no template explains is named ``unknown``;
repeated rows give repeated results. A template is a list of whole wordings, notices and full texts; only a block
that equals one of them word by word is exact. Lines of at most twelve words that state a copyright name the holder
and are not compared.
"""

from __future__ import annotations

import difflib
import re
from collections import Counter
from pathlib import Path

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Words that make a line a candidate.
MARKS = ("licens", "licenc", "copyright", "permission is", "redistribut", "warrant", "spdx", "creativecommons", "cc by", "cc-by", "public domain")

#: The usual notices of public licences, each a whole wording.
NOTICES = {
    "MIT": ("Released under the MIT License.", "Licensed under the MIT license.", "SPDX-License-Identifier: MIT"),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "SPDX-License-Identifier: Apache-2.0",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "SPDX-License-Identifier: GPL-3.0-or-later",
        "SPDX-License-Identifier: GPL-3.0-only",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.",
    ),
    "GPL-2.0": (
        "This program is licensed under the GNU General Public License, version 2.",
        "SPDX-License-Identifier: GPL-2.0-only",
        "SPDX-License-Identifier: GPL-2.0-or-later",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    ),
    **{
        f"CC-{k}-4.0": (
            f"Licensed under CC {k} 4.0.",
            f"This work is licensed under a Creative Commons {name} 4.0 International License.",
            f"SPDX-License-Identifier: CC-{k}-4.0",
            f"https://creativecommons.org/licenses/{k.lower()}/4.0/",
        )
        for k, name in (("BY-NC", "Attribution-NonCommercial"), ("BY", "Attribution"), ("BY-SA", "Attribution-ShareAlike"))
    },
    "BSD-3-Clause": ("Released under the BSD 3-Clause License.", "SPDX-License-Identifier: BSD-3-Clause"),
    "MPL-2.0": (
        "Licensed under the Mozilla Public License, version 2.0.",
        "SPDX-License-Identifier: MPL-2.0",
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    ),
}
#: Titles that a full text may or may not bear.
TITLES = {"MIT": ("MIT License", "The MIT License", "The MIT License (MIT)"), "BSD-3-Clause": ("BSD 3-Clause License", "The BSD 3-Clause License")}
WORDS = re.compile(r"[^\W_]+(?:[.-][^\W_]+)*")
HOLDER = re.compile(r"\W*copyright\s*(?:\(c\)|©|[0-9]{4})", re.IGNORECASE)
RUN = 4


def full_templates() -> dict[str, tuple[str, ...]]:
    """Notices and full texts by licence; the full texts lie beside this file."""
    out = {}
    for name, notices in NOTICES.items():
        file = Path(__file__).parent / "wordings" / f"{name}.txt"
        whole = (file.read_text(encoding="utf-8"),) if file.exists() else ()
        out[name] = (*whole, *(f"{t}\n{w}" for t in TITLES.get(name, ()) for w in whole), *notices)
    return out


def line_words(line: str) -> list[str]:
    found = [w.lower() for w in WORDS.findall(line)]
    return [] if len(found) <= 12 and HOLDER.match(line) else found


def text_words(text: str) -> list[str]:
    return [w for line in text.split("\n") for w in line_words(line)]


class Scanner:
    def __init__(self, templates: dict[str, tuple[str, ...]], level: int = 3):
        kind = zstandard.DICT_TYPE_RAWCONTENT
        self.plain = zstandard.ZstdCompressor(level=level, write_content_size=False, write_checksum=False)
        self.given = {}
        for name, ts in templates.items():
            held = zstandard.ZstdCompressionDict("\n".join(ts).encode(), dict_type=kind)
            held.precompute_compress(level=level)
            self.given[name] = zstandard.ZstdCompressor(level=level, write_content_size=False, write_checksum=False, dict_data=held)
        lists = [(name, text_words(t)) for name, ts in templates.items() for t in ts]
        self.wordings = [(name, ws, Counter(ws)) for name, ws in lists]
        self.whole = {tuple(ws) for _, ws in lists}
        self.runs = {tuple(ws[k:k + RUN]) for _, ws in lists for k in range(len(ws) - RUN + 1)}

    def rank(self, block: str) -> list[tuple[str, int]]:
        """Templates by bytes saved, most first, by name where equal."""
        data = block.encode("utf-8", "replace")
        alone = len(self.plain.compress(data))
        return sorted(((n, alone - len(c.compress(data))) for n, c in self.given.items()), key=lambda x: (-x[1], x[0]))

    @staticmethod
    def differences(own: list[str], wording: list[str]) -> tuple[int, int]:
        """Words of the block that the wording lacks in that order, and words of the wording that the block lacks."""
        lead = 0
        while lead < min(len(own), len(wording)) and own[lead] == wording[lead]:
            lead += 1
        a, b = own[lead:], wording[lead:]
        tail = 0
        while tail < min(len(a), len(b)) and a[-1 - tail] == b[-1 - tail]:
            tail += 1
        a, b = a[:len(a) - tail], b[:len(b) - tail]
        same = sum(m.size for m in difflib.SequenceMatcher(None, a, b, autojunk=False).get_matching_blocks()) if a and b else 0
        return len(a) - same, len(b) - same

    def identify(self, block: str, most: float = 0.34) -> tuple[str, int, int, int]:
        """License, bytes saved, words that differ either way, words. The wording that leaves fewest of the block's words, then lacks fewest of its own, wins."""
        ranked = self.rank(block)
        gains = dict(ranked)
        own = text_words(block)
        total, bag = len(own), Counter(own)
        least = lambda w: ((bag - w[2]).total(), (w[2] - bag).total())
        bounds = sorted(((*least(w), -gains[w[0]], w[0], k) for k, w in enumerate(self.wordings) if gains[w[0]] > 0))
        best = None
        for extra, lack, lost, name, k in bounds:
            if extra > most * total or (best and (extra, lack) > best[:2]):
                continue
            found = (*self.differences(own, self.wordings[k][1]), lost, name)
            best = min(best, found) if best else found
        if best and total and best[0] <= most * total:
            return best[3], -best[2], best[0] + best[1], total
        return "unknown", max(0, ranked[0][1]) if ranked else 0, total, total

    def blocks(self, text: str, gap: int = 2) -> list[tuple[int, str]]:
        """(first line number, block): marker lines with the lines about them that belong to a wording."""
        lines = text.split("\n")
        words = [(k, w) for k, line in enumerate(lines) for w in line_words(line)]
        stream = [w for _, w in words]
        covered = [False] * len(words)
        for k in range(len(words) - RUN + 1):
            if tuple(stream[k:k + RUN]) in self.runs:
                covered[k:k + RUN] = [True] * RUN
        size, hit = Counter(k for k, _ in words), Counter(k for (k, _), c in zip(words, covered, strict=True) if c)
        marked = [any(m in line.lower() for m in MARKS) for line in lines]
        pieces: list[list[int]] = []
        for k in range(len(lines)):
            if marked[k] or (hit[k] and 2 * hit[k] >= size[k]):
                if pieces and pieces[-1][1] == k - 1:
                    pieces[-1][1] = k
                else:
                    pieces.append([k, k])
        # A piece that is a whole wording stands alone unless a longer wording runs on over its edge; others go on over blank and a few other lines.
        spans, before, closed = [], [], True
        for a, b in pieces:
            own = [w for line in lines[a:b + 1] for w in line_words(line)]
            alone = tuple(own) in self.whole
            between = sum(1 for k in range(spans[-1][1] + 1, a) if size[k]) if spans else gap + 1
            if between <= gap and (not (closed or alone) or (not between and (*before[-2:], *own[:2]) in self.runs)):
                spans[-1][1], closed = b, False
            else:
                spans.append([a, b])
                closed = alone
            before = own
        return [(a, "\n".join(lines[a:b + 1])) for a, b in spans if any(marked[a:b + 1])]


def scan(docs: DataFrame, templates: dict[str, str | tuple[str, ...]] | None = None, *, text: str = "text") -> DataFrame:
    """One row for each candidate block: doc_id, line, license, saved, n_diff, n_words and exact (no word differs either way)."""
    held = {n: (t,) if isinstance(t, str) else tuple(t) for n, t in (templates or full_templates()).items()}
    rows = docs.select("doc_id", F.col(text).alias("_text"))
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def step(batches):
        scanner = Scanner(held)
        for batch in batches:
            take, line, name, saved, diff, words = [], [], [], [], [], []
            for k, t in enumerate(batch.column(1).to_pylist()):
                low = t.lower() if t else ""
                if not any(m in low for m in MARKS):
                    continue
                for at, block in scanner.blocks(t):
                    found = scanner.identify(block)
                    for out, v in zip((take, line, name, saved, diff, words), (k, at, *found)):
                        out.append(v)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(take, pa.int32())), pa.array(line, pa.int32()), pa.array(name, pa.string()), pa.array(saved, pa.int64()), pa.array(diff, pa.int64()), pa.array(words, pa.int64())],
                ["doc_id", "line", "license", "saved", "n_diff", "n_words"],
            )

    out = rows.mapInArrow(step, f"doc_id {id_type}, line int, license string, saved bigint, n_diff bigint, n_words bigint")
    return out.withColumn("exact", (F.col("n_diff") == 0) & (F.col("license") != "unknown"))
