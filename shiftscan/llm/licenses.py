"""License scans by conditional compression.

Blocks of neighbouring lines that speak of licensing are candidates. Each is
compressed once plainly and once with every template as a raw zstandard dictionary;
templates are ranked by how much of the block they explain away. The winner is
confirmed on exact wording: its statement closest to the block is aligned word by
word, the differences are reported, and it counts only if they are few and none of
the words that tell this license from its kin is among them; else the next is tried.

A run of candidate lines that no license confirms grows: to its paragraph, and then
over blank lines to all neighbouring paragraphs that have such runs. It never takes in
lines that are confirmed already. What grew and is still not confirmed is reported as
the runs it came from.

Defined results: a null or empty text has no blocks; lines are judged in full however
long; a repeated block is reported each time; rows are independent; other columns
stay; empty tables are fine.
"""

from __future__ import annotations

import difflib
import re
from functools import lru_cache

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import need, prepare

#: Public license notices, as (statement, words that must be there).
TEMPLATES: dict[str, tuple[tuple[str, tuple[str, ...]], ...]] = {
    "MIT": (
        ("Released under the MIT License.", ("mit",)),
        ("Licensed under the MIT License.", ("mit",)),
        ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction", ("granted", "charge", "restriction")),
    ),
    "Apache-2.0": (
        ("Licensed under the Apache License, Version 2.0.", ("apache", "2.0")),
        ("Released under the Apache License, Version 2.0.", ("apache", "2.0")),
        ("you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0", ("compliance", "file")),
    ),
    "GPL-3.0": (
        ("This work is licensed under the GNU General Public License, version 3.", ("gnu", "general", "3")),
        ("This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License", ("gnu", "general", "3")),
    ),
    "GPL-2.0": (
        ("This work is licensed under the GNU General Public License, version 2.", ("gnu", "general", "2")),
        ("This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License", ("gnu", "general", "2")),
    ),
    "LGPL-3.0": (("This work is licensed under the GNU Lesser General Public License, version 3.", ("gnu", "lesser", "3")),),
    "MPL-2.0": (("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", ("mozilla",)), ("Licensed under the Mozilla Public License, version 2.0.", ("mozilla", "2.0"))),
    "BSD-3-Clause": (("Licensed under the BSD 3-Clause License.", ("bsd", "3-clause")), ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", ("redistribution", "binary"))),
    "CC-BY-4.0": (("Licensed under CC BY 4.0.", ("cc", "by", "4.0")), ("This work is licensed under a Creative Commons Attribution 4.0 International License.", ("commons", "attribution", "4.0"))),
    "CC-BY-SA-4.0": (("Licensed under CC BY-SA 4.0.", ("cc", "by-sa", "4.0")), ("This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.", ("commons", "attribution-sharealike", "4.0"))),
    "CC-BY-NC-4.0": (("Licensed under CC BY-NC 4.0.", ("cc", "by-nc", "4.0")), ("This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.", ("commons", "attribution-noncommercial", "4.0"))),
    "CC0-1.0": (("Dedicated to the public domain under CC0 1.0.", ("cc0",)),),
}
#: Headings that are a line of their own.
TITLES = {"mit license": "MIT", "the mit license": "MIT", "mit license mit": "MIT", "the mit license mit": "MIT", "bsd 3-clause license": "BSD-3-Clause", "the 3-clause bsd license": "BSD-3-Clause"}
#: Headings of long license texts.
HEADINGS = {
    "Apache-2.0": ("Apache License Version 2.0, January 2004", ("apache", "2.0", "2004")),
    "GPL-3.0": ("GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007", ("gnu", "general", "3")),
    "GPL-2.0": ("GNU GENERAL PUBLIC LICENSE Version 2, June 1991", ("gnu", "general", "2")),
    "LGPL-3.0": ("GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007", ("gnu", "lesser", "3")),
    "MPL-2.0": ("Mozilla Public License Version 2.0", ("mozilla", "2.0")),
}
#: Identifiers of a license in a line of its own kind.
SPDX = {name: (name,) for name in TEMPLATES} | {f"{g}GPL-{v}.0": tuple(f"{g}GPL-{v}.0{end}" for end in ("", "-only", "-or-later")) for g, v in (("", 3), ("", 2), ("L", 3))}
#: Whole texts, for the ranking.
WHOLE = {
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
}
HINT = r"(?i)licen[sc]|copyright|redistribut|public domain|permission is|creative commons|spdx"
_LINE = re.compile(HINT)
_WORD = re.compile(r"[^\W_][\w.+/-]*", re.U)


def words_of(text: str) -> list[str]:
    return [w.rstrip(".-/+").lower() for w in _WORD.findall(text)]


def _lines(text: str) -> tuple[list[tuple[int, int]], list[tuple[int, int]]]:
    """All lines as code points, and the runs of neighbouring candidate lines as line numbers."""
    lines: list[tuple[int, int]] = []
    runs: list[tuple[int, int]] = []
    at = 0
    for k, line in enumerate(text.split("\n")):
        lines.append((at, at + len(line)))
        if _LINE.search(line):
            if runs and k == runs[-1][1] + 1:
                runs[-1] = (runs[-1][0], k)
            else:
                runs.append((k, k))
        at += len(line) + 1
    return lines, runs


def blocks(text: str) -> list[tuple[int, int]]:
    """Runs of neighbouring candidate lines, as code points."""
    lines, runs = _lines(text)
    return [(lines[a][0], lines[b][1]) for a, b in runs]


class Scanner:
    def __init__(self, templates: dict, most: float):
        self.most = most
        self.plain = zstandard.ZstdCompressor(level=9)
        self.templates = {}
        for name, statements in templates.items():
            spdx = tuple((f"SPDX-License-Identifier: {x}", ("spdx-license-identifier", x.lower())) for x in SPDX[name])
            statements = (*statements, *spdx, *([HEADINGS[name]] if name in HEADINGS else []))
            held = [*(s for s, _ in statements), *(t for t, n in TITLES.items() if n == name), WHOLE.get(name, "")]
            raw = zstandard.ZstdCompressionDict("\n".join(held).encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            self.templates[name] = (zstandard.ZstdCompressor(level=9, dict_data=raw), [(words_of(s), need_) for s, need_ in statements])

    def ranked(self, block: str) -> list[tuple[float, str]]:
        """(reduction, template), largest first."""
        data = block.encode("utf-8", "replace")
        size = len(self.plain.compress(data))
        return sorted(((1 - len(c.compress(data)) / size, name) for name, (c, _) in self.templates.items()), key=lambda x: (-x[0], x[1]))

    def differences(self, name: str, block: list[str]) -> list[str] | None:
        """Words to take from (-) or add to (+) the closest statement; null if the wording is not this license's."""
        best: list[str] | None = None
        if TITLES.get(" ".join(block)) == name:
            return []
        for statement, must in self.templates[name][1]:
            # Only around the longest common run: a block may hold much else.
            n, slack = len(statement), int(self.most * len(statement))
            run = difflib.SequenceMatcher(None, statement, block, autojunk=False).find_longest_match(0, n, 0, len(block))
            near = block[max(0, run.b - run.a - slack) : run.b - run.a + n + slack]
            ops = [x for x in difflib.SequenceMatcher(None, statement, near, autojunk=False).get_opcodes() if x[0] != "equal"]
            # What stands before and after the statement is not its wording.
            gone = [w for _, a, b, _, _ in ops for w in statement[a:b]]
            new = [w for _, a, b, c, d in ops if 0 < a and b < len(statement) for w in near[c:d]]
            if len(gone) + len(new) <= self.most * len(statement) and not set(must) & set(gone):
                found = [f"-{w}" for w in gone] + [f"+{w}" for w in new]
                if best is None or len(found) < len(best):
                    best = found
        return best

    def judged(self, block: str) -> dict | None:
        """What confirms a block, or null."""
        words = words_of(block)
        for rank, (gain, name) in enumerate(self.ranked(block), 1):
            if gain <= 0:
                break
            if (found := self.differences(name, words)) is not None:
                return {"license": name, "reduction": gain, "rank": rank, "differences": found}
        return None

    def scan(self, text: str) -> list[dict]:
        lines, runs = _lines(text)
        out: dict[tuple[int, int], dict] = {}

        def tried(groups) -> None:
            """Confirms groups of runs as one block each."""
            nonlocal runs
            for low, high, some in groups:
                if (found := self.judged(text[lines[low][0] : lines[high][1]])) is not None:
                    out[low, high] = found
                    runs = [r for r in runs if r not in some]

        tried([(a, b, [(a, b)]) for a, b in runs])
        if runs:
            taken = [False] * len(lines)
            for low, high in out:
                taken[low : high + 1] = [True] * (high + 1 - low)
            # A line without a word, or one that is confirmed, ends a paragraph.
            ends = [t or not _WORD.search(text, *at) for t, at in zip(taken, lines)]
            paragraphs: list[tuple[int, int, list[tuple[int, int]]]] = []
            for run in runs:
                low, high = run
                if paragraphs and low <= paragraphs[-1][1]:
                    paragraphs[-1][2].append(run)
                    continue
                while low > 0 and not ends[low - 1]:
                    low -= 1
                while high + 1 < len(lines) and not ends[high + 1]:
                    high += 1
                paragraphs.append((low, high, [run]))
            tried(p for p in paragraphs if [p[:2]] != p[2])
            notices: list[tuple[int, int, list[tuple[int, int]]]] = []
            for low, high, some in paragraphs:
                if some[0] not in runs:
                    continue
                if notices and all(ends[k] and not taken[k] for k in range(notices[-1][1] + 1, low)):
                    notices[-1] = (notices[-1][0], high, notices[-1][2] + some)
                else:
                    notices.append((low, high, some))
            tried(p for p in notices if p not in paragraphs)
        nothing = {"license": None, "reduction": 0.0, "rank": 0, "differences": []}
        return [{"start": lines[a][0], "end": lines[b][1]} | got for (a, b), got in sorted([*out.items(), *((r, nothing) for r in runs)], key=lambda x: x[0])]


@lru_cache(maxsize=2)
def _scanner(most: float) -> Scanner:
    return Scanner(TEMPLATES, most)


def scan(docs: DataFrame, most: float = 0.2, column: str = "text", into: str = "licenses") -> DataFrame:
    """``docs`` and array ``into`` of (start, end, license, reduction, rank, differences), one per block.

    ``most``: share of a statement's words that may differ. ``license`` is null where no wording was confirmed.
    """
    need(docs, column)
    prepare(docs.sparkSession)
    kind = "array<struct<start: int, end: int, license: string, reduction: double, rank: int, differences: array<string>>>"
    item = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("license", pa.string()), ("reduction", pa.float64()), ("rank", pa.int32()), ("differences", pa.list_(pa.string()))]))

    @F.arrow_udf(kind)
    def work(texts: pa.Array) -> pa.Array:
        return pa.array([_scanner(most).scan(t) if t else [] for t in texts.to_pylist()], item)

    text = F.col(column).cast("string")
    return docs.withColumn(into, F.coalesce(work(F.when(text.rlike(HINT), text)), F.array().cast(kind)))
