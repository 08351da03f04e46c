"""Operator 9: license scan by conditional compression.

A candidate block is a run of lines around one that names a license, with lines before and after it as far as the longest template's words reach, one to a
line; lines without words don't count. Blocks that lack too many of every template's words to be confirmed are left out, each other one is compressed by
zstandard alone and with every template as raw dictionary; templates are ranked by the relative size reduction, and the
winner is confirmed if the wording differs from the template's by at most ``max_diff`` of its words, none of them a key word of the template.
Empty tables give no rows; very long texts are read whole; further columns aren't read. Every template has one of ``TRIGGERS`` among its key words, so the line filter, which runs in generated code before any Python, loses nothing that could be confirmed.

Result: one row per confirmed notice: doc_id, line where it begins (from 0), license, reduction, n_diff, diff (``-word +word``). A block counts if its first and last
line hold words of the notice. Of blocks whose notices share words the one of most words counts, twice its differences taken off, then the one with the largest reduction, and so of
notices that begin on one line; ties go to the template named first. Null and empty texts have no lines. Repeated rows give repeated results."""

from __future__ import annotations

import difflib
import math
import re
from collections import Counter
from collections.abc import Iterator
from itertools import accumulate

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: name: (wording, key words that have to be there)
TEMPLATES: dict[str, tuple[str, tuple[str, ...]]] = {
    "mit-notice": ("Released under the MIT License.", ("mit", "license")),
    "mit-grant": ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction", ("permission", "granted", "charge", "software")),
    "apache-2.0-notice": ("Licensed under the Apache License, Version 2.0.", ("apache", "license", "2", "0")),
    "apache-2.0-header": ("Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.", ("apache", "license", "compliance")),
    "gpl-3.0-notice": ("This work is licensed under the GNU General Public License, version 3.", ("gnu", "general", "license", "3")),
    "gpl-2.0-notice": ("This work is licensed under the GNU General Public License, version 2.", ("gnu", "general", "license", "2")),
    "lgpl-3.0-notice": ("This work is licensed under the GNU Lesser General Public License, version 3.", ("gnu", "lesser", "license", "3")),
    "cc-by-4.0-notice": ("Licensed under CC BY 4.0.", ("licensed", "cc", "by", "4", "0")),
    "cc-by-sa-4.0-notice": ("Licensed under CC BY-SA 4.0.", ("licensed", "cc", "by", "sa", "4", "0")),
    "cc-by-nc-4.0-notice": ("Licensed under CC BY-NC 4.0.", ("licensed", "cc", "by", "nc", "4", "0")),
    "bsd-redistribution": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:", ("redistribution", "source", "binary", "permitted")),
    "mpl-2.0-header": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", ("mozilla", "license", "2", "0")),
    "mit-text": ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.", ("permission", "granted", "charge", "software", "sublicense", "merchantability")),
    "isc-text": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.", ("permission", "fee", "granted", "disclaims")),
    "bsd-2-clause-text": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.", ("redistribution", "source", "binary", "permitted", "disclaimer", "exemplary")),
    "apache-2.0-boilerplate": ("Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.", ("apache", "license", "compliance", "governing")),
    "gpl-3.0-header": ("This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.", ("gnu", "general", "license", "3", "redistribute")),
    "mpl-2.0-text": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.", ("mozilla", "license", "2", "0", "mpl")),
}
TRIGGERS = ("license", "licensed", "permission", "redistribution")
MAX_DIFF, LEVEL = 0.15, 19
_FILTER = r"(?i)\b(" + "|".join(TRIGGERS) + r")\b"


def wording(text: str) -> list[str]:
    return re.findall(r"[^\W_]+", text.lower())


def differences(block: list[str], template: list[str]) -> tuple[int, list[str]]:
    """Words lost and put in, over the part of the block from the first to the last word that they share."""
    ops = [o for o in difflib.SequenceMatcher(None, template, block, autojunk=False).get_opcodes()]
    if not any(o[0] == "equal" for o in ops):
        return len(template), [f"-{w}" for w in template]
    lost, put = [], []
    for k, (tag, a0, a1, b0, b1) in enumerate(ops):
        if tag != "equal":
            lost += template[a0:a1]
            if 0 < k < len(ops) - 1:
                put += block[b0:b1]
    return max(len(lost), len(put)), [f"-{w}" for w in lost] + [f"+{w}" for w in put]


class Scanner:
    def __init__(self, templates: dict[str, tuple[str, tuple[str, ...]]] = TEMPLATES, max_diff: float = MAX_DIFF):
        import zstandard as z

        self.templates, self.max_diff = templates, max_diff
        self.words = {k: wording(t) for k, (t, _) in templates.items()}
        self.bags = {k: Counter(w) for k, w in self.words.items()}
        self.plain = z.ZstdCompressor(level=LEVEL)
        self.given = {k: z.ZstdCompressor(level=LEVEL, dict_data=z.ZstdCompressionDict(t.encode(), dict_type=z.DICT_TYPE_RAWCONTENT)) for k, (t, _) in templates.items()}
        self.seen: dict[str, tuple | None] = {}

    def block(self, text: str) -> tuple[float, str, int, str] | None:
        """(reduction, license, n_diff, diff) of the confirmed winner."""
        if text in self.seen:
            return self.seen[text]
        raw = text.encode("utf-8", "surrogatepass")
        alone = len(self.plain.compress(raw))
        ranked = sorted(((round(1 - len(c.compress(raw)) / alone, 6), k) for k, c in self.given.items()), key=lambda x: -x[0])
        found = None
        have = wording(text)
        for reduction, k in ranked:
            # winners share the top within a tenth; the exact wording decides among them
            if reduction < ranked[0][0] - 0.1:
                break
            n, diff = differences(have, self.words[k])
            keys = self.templates[k][1]
            if n <= self.max_diff * len(self.words[k]) and not any(f"-{w}" in diff for w in keys) and (found is None or n < found[2]):
                found = (reduction, k, n, " ".join(diff))
        if len(self.seen) > 100_000:
            self.seen.clear()
        self.seen[text] = found
        return found

    def runs(self, of: dict[int, list[str]], full: list[int], triggers: set[int]) -> set[tuple[int, int]]:
        """(first, last line) of the blocks that hold enough of some template's words to be confirmed, and that lose words if their first or last line goes.

        Each block grows from a trigger line; a notice that is confirmed has its first and its last words in such a block."""
        out = set()
        words_of = [of[i] for i in full]
        for name, bag in self.bags.items():
            n = sum(bag.values())
            need, reach = (1 - self.max_diff) * n - 1e-9, math.ceil((1 + self.max_diff) * n)
            keys = set(self.templates[name][1])
            # lines that share words with the template, and what each has of it
            part = [{w: w_n for w, w_n in Counter(w for w in ws if w in bag).items()} for ws in words_of]
            for at, i in enumerate(full):
                if i not in triggers or not keys & part[at].keys():
                    continue
                first, before = at, 0
                while first >= 0:
                    have, put, held = Counter(), 0, 0
                    if part[first]:
                        for last in range(first, len(full)):
                            for w, k in part[last].items():
                                held += min(bag[w], have[w] + k) - min(bag[w], have[w])
                                have[w] += k
                            put += len(words_of[last]) if first < last else 0
                            if last >= at and held >= need and part[last]:
                                out.add((full[first], full[last]))
                            if put >= reach + len(words_of[last]):
                                break
                    first -= 1
                    if first >= 0:
                        if before >= reach:
                            break
                        before += len(words_of[first])
        return out

    def lines(self, text: str) -> list[tuple[int, str, float, int, str]]:
        rows = text.split("\n")
        named = re.compile(_FILTER)
        triggers = {i for i, line in enumerate(rows) if named.search(line)}
        if not triggers:
            return []
        of = {i: w for i, line in enumerate(rows) if (w := wording(line))}
        full = sorted(of)
        began = dict(zip(full, [0, *accumulate(len(of[i]) for i in full)]))
        runs = self.runs(of, full, triggers)
        found = []
        for s, e in runs:
            have = [w for i in range(s, e + 1) for w in of.get(i, ())]
            got = self.block("\n".join(rows[s : e + 1]))
            if not got:
                continue
            same = [m for m in difflib.SequenceMatcher(None, self.words[got[1]], have, autojunk=False).get_matching_blocks() if m.size]
            x, y = same[0].b, same[-1].b + same[-1].size
            if x < len(of[s]) and y > len(have) - len(of[e]):
                found.append((2 * got[2] - len(self.words[got[1]]), -got[0], e - s, s, began[s] + x, began[s] + y, got))
        taken, out = [], {}
        for *_, s, x, y, got in sorted(found, key=lambda f: f[:5]):
            if all(y <= a or b <= x for a, b in taken):
                taken.append((x, y))
                out.setdefault(s, (s, got[1], got[0], got[2], got[3]))
        return [out[s] for s in sorted(out)]


def license_scan(docs: DataFrame, templates: dict[str, tuple[str, tuple[str, ...]]] = TEMPLATES, max_diff: float = MAX_DIFF) -> DataFrame:
    hit = docs.select("doc_id", "text").filter(F.col("text").rlike(_FILTER))

    @F.pandas_udf("array<struct<line:int,license:string,reduction:double,n_diff:int,diff:string>>")
    def scan(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scanner = Scanner(templates, max_diff)
        for texts in parts:
            yield pd.Series([[{"line": a, "license": b, "reduction": c, "n_diff": d, "diff": e} for a, b, c, d, e in scanner.lines(t)] for t in texts], dtype=object)

    return hit.select("doc_id", F.explode(scan("text")).alias("x")).select("doc_id", "x.line", "x.license", "x.reduction", "x.n_diff", "x.diff")
