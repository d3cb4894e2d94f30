"""License scan: MinHash bands over overlapping text windows retrieve templates, exact shingle containment verifies them.

Every template has a shingle width of five words (all its words, if fewer). Its MinHash signature has one value for each band of the hash
space, the smallest shingle hash there (one hash function, one permutation). A text is cut into overlapping windows of twice a template's
reach, so that every match lies whole in one of them; a window that holds enough of the band values retrieves the template. Retrieved windows
are verified exactly: hits of the template's shingles within its own length widened by half
are a match if they hold 0.8 or more of its shingles (all, under twelve words).

The band settings guarantee retrieval. Of a template's n shingles a match lacks at most n - need, so it holds at least bands - (n - need) of its
band values, wherever the window lies; where that is one or more, retrieval is certain (templates of up to about 120 words), and that many are
asked for. A longer template is missed only if all its band values are among the lacking fifth, a chance of at most
0.2 ** bands, below 1e-12 for 18 bands or more; ``miss_chance`` states it for each template, and a test holds it.

The words that tell a license from its relatives, such as the version,
must stand inside the match, and it must not hold the name of a relative. A license has several wordings: notices made
of ``LEADS`` and ``NAMES``, tags, longer notices and full texts (``license_texts``).

Defined cases: null and blank texts match nothing; words are compared without case (A to Z) and punctuation;
overlapping matches of one license are one span; a license may match several times; templates of equal wording (ties) are all found; without templates the result
is empty; a license named without its version is not reported where versions differ; repeated rows match alike; a very long text is scanned in
blocks; an empty table gives an empty result; other columns are left out, whatever their names.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator, Mapping, Sequence
from dataclasses import dataclass
from importlib import resources
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.llm import common, near_dup

WIDTH = 5
CONTAINMENT = 0.8
#: Words of a text that one numpy block holds; blocks overlap by a shingle.
BLOCK_WORDS = 1 << 18
#: Slots of the filter before the lookup of band values.
SLOTS = 1 << 20
#: Bits of a hash that name its band: 32 bands.
BAND_BITS = 5
#: Templates of up to so many words are notices, whose names and versions must all be in the match.
NOTICE_WORDS = 120
#: Shorter templates must be whole: without its lead the name of a license is a mere mention.
WHOLE_WORDS = 12

#: Well-known short notices of public licenses and reservations, each under its own name.
TEMPLATES = {
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "mit": "Released under the MIT License.",
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "all-rights-reserved": "All rights reserved.",
    "mit-text": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), "
        "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell "
        "copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"
    ),
    "gpl-notice": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by "
        "the Free Software Foundation, either version 3 of the License, or (at your option) any later version."
    ),
    "bsd-text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-sa-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
}
#: What stands before the name of a license in a notice.
LEADS = ("under", "under the", "under a", "under the terms of", "under the terms of the", "under the terms and conditions of the", "under terms of the", "subject to the", "subject to the terms of the", "governed by the", "covered by the", "licensed as", "license:")


def _gnu(kind: str, short: str, *versions: str) -> tuple[str, ...]:
    numbers = [w for v in versions for w in (f"version {v}", f"v{v}", v)]
    long = [f"{g}{kind} General Public License {n}" for g in ("GNU ", "") for n in numbers] + [f"version {v} of the GNU {kind} General Public License" for v in versions]
    return tuple(long + [f"{g}{short}{x}" for g in ("GNU ", "") for v in versions for x in (f" version {v}", f" v{v}", f"v{v}", f" {v}", f"-{v}")])


def _cc(words: str, code: str, *versions: str) -> tuple[str, ...]:
    kinds = ("International License", "International", "Unported License", "License", "")
    return tuple(
        [f"Creative Commons {w} {v} {k}" for w in dict.fromkeys((words, words.replace("-", " "))) for v in versions for k in kinds]
        + [f"{c}{sep}{code} {v}" for c in ("CC", "Creative Commons") for sep in (" ", "-") for v in versions]
        + [f"CC {code.replace('-', ' ')} {v}" for v in versions]
    )


#: Names of a license as notices write them.
NAMES = {
    "0bsd": ("Zero-Clause BSD License", "BSD Zero Clause License"),
    "agpl-3.0": _gnu("Affero", "AGPL", "3", "3.0"),
    "apache-2.0": tuple(f"{a}{v}" for a in ("Apache License", "Apache Software License", "Apache") for v in (" Version 2.0", " 2.0", " v2.0", " v2", " Version 2", "-2.0", " 2")),
    "artistic-2.0": ("Artistic License 2.0", "Artistic License Version 2.0"),
    "bsd-2-clause": ("BSD 2-Clause License", "2-Clause BSD License", "Simplified BSD License", "BSD 2-Clause", "BSD-2-Clause License"),
    "bsd-3-clause": ("BSD 3-Clause License", "3-Clause BSD License", "New BSD License", "Modified BSD License", "Revised BSD License", "BSD 3-Clause", 'BSD 3-Clause "New" or "Revised" License'),
    "bsl-1.0": ("Boost Software License 1.0", "Boost Software License Version 1.0"),
    "cc-by-4.0": _cc("Attribution", "BY", "4.0"),
    "cc-by-3.0": _cc("Attribution", "BY", "3.0"),
    "cc-by-sa-4.0": _cc("Attribution-ShareAlike", "BY-SA", "4.0"),
    "cc-by-sa-3.0": _cc("Attribution-ShareAlike", "BY-SA", "3.0"),
    "cc-by-nc-4.0": _cc("Attribution-NonCommercial", "BY-NC", "4.0"),
    "cc-by-nc-sa-4.0": _cc("Attribution-NonCommercial-ShareAlike", "BY-NC-SA", "4.0"),
    "cc-by-nc-nd-4.0": _cc("Attribution-NonCommercial-NoDerivatives", "BY-NC-ND", "4.0"),
    "cc-by-nd-4.0": _cc("Attribution-NoDerivatives", "BY-ND", "4.0"),
    "cc0-1.0": ("CC0 1.0", "CC0 1.0 Universal", "Creative Commons CC0 1.0", "Creative Commons Zero 1.0", "CC0-1.0"),
    "epl-1.0": ("Eclipse Public License 1.0", "Eclipse Public License v1.0", "Eclipse Public License Version 1.0"),
    "epl-2.0": ("Eclipse Public License 2.0", "Eclipse Public License v2.0", "Eclipse Public License Version 2.0"),
    "gfdl-1.3": ("GNU Free Documentation License Version 1.3", "GFDL 1.3"),
    "gpl-2.0": _gnu("", "GPL", "2", "2.0"),
    "gpl-3.0": _gnu("", "GPL", "3", "3.0"),
    "isc": ("ISC License", "ISC"),
    "lgpl-2.1": _gnu("Lesser", "LGPL", "2.1"),
    "lgpl-3.0": _gnu("Lesser", "LGPL", "3", "3.0"),
    "mit": ("MIT License", "MIT", "MIT/X11 License", "Expat License", "MIT-License"),
    "mpl-1.1": ("Mozilla Public License 1.1", "Mozilla Public License Version 1.1", "Mozilla Public License v1.1", "MPL 1.1"),
    "mpl-2.0": ("Mozilla Public License 2.0", "Mozilla Public License Version 2.0", "Mozilla Public License v2.0", "Mozilla Public License v. 2.0", "MPL 2.0", "MPL-2.0"),
    "unlicense": ("Unlicense",),
    "zlib": ("zlib License", "zlib/libpng License"),
}
#: As German words and the like, these are names only after "under".
_BARE = frozenset(("MIT", "ISC"))

_BSD_1 = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
)
_BSD_NAMES = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
_BSD_2 = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE '
    "ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS "
    "OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY "
    "OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)


def _gnu_notice(what: str, kind: str, version: str) -> str:
    return (
        f"This {what} is free software; you can redistribute it and/or modify it under the terms of the GNU {kind} General Public License as published by "
        f"the Free Software Foundation; either version {version} of the License, or (at your option) any later version."
    )


#: Longer notices and the full texts of short licenses.
TEXTS = {
    "0bsd": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. "
        'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE',
    ),
    "agpl-3.0": (_gnu_notice("program", "Affero", "3"),),
    "apache-2.0": (
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 '
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. '
        "See the License for the specific language governing permissions and limitations under the License.",
    ),
    "bsd-2-clause": (_BSD_1 + _BSD_2,),
    "bsd-3-clause": (_BSD_1 + _BSD_NAMES + _BSD_2,),
    "bsl-1.0": ("Distributed under the Boost Software License, Version 1.0. (See accompanying file LICENSE_1_0.txt or copy at http://www.boost.org/LICENSE_1_0.txt)",),
    "gpl-2.0": (_gnu_notice("program", "", "2"), _gnu_notice("program", "", "2").replace("either version 2 of the License, or (at your option) any later version", "version 2 of the License")),
    "isc": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
        "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    ),
    "lgpl-2.1": (_gnu_notice("library", "Lesser", "2.1"), _gnu_notice("program", "Lesser", "2.1")),
    "lgpl-3.0": (_gnu_notice("library", "Lesser", "3"), _gnu_notice("program", "Lesser", "3")),
    "mit": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), "
        "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell "
        "copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: "
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. '
        "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, "
        "OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    "mpl-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",),
    "unlicense": (
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, "
        "for any purpose, commercial or non-commercial, and by any means.",
    ),
    "zlib": (
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. "
        "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: "
        "1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software.",
    ),
}
#: Phrases of long texts that the match must hold, and that it must not hold (of a relative with nearly the same text).
WANTED = {
    "apache-2.0": "version 20",
    "artistic-1.0": "artistic license",
    "bsd-3-clause": "neither the name",
    "gfdl-1.3": "version 13",
    "gpl-2.0": "version 2 june 1991",
    "gpl-3.0": "refers to version 3 of the gnu general public license",
    "isc": "provided that the above copyright notice",
    "lgpl-2.1": "version 21 february 1999",
    "lgpl-3.0": "version 3 of the gnu lesser general public license",
    "mpl-1.1": "version 11",
    "mpl-2.0": "version 20",
}
BARRED = {"bsd-2-clause": "neither the name", "0bsd": "provided that"}
#: Words that tell a notice from those of related licenses: names, and versions as numbers.
_TELLING = re.compile(
    rb"v?\d{1,3}|\d?clause|(?:gpl|lgpl|agpl|mpl|apache|cc|gfdl)v?\d+\w*|mit|expat|mitx11|apache|affero|lesser|agpl|lgpl|gpl|mozilla|mpl|bsd|isc|zlib|boost|unlicense|eclipse|"
    rb"cc0|by(?:nc|sa|nd)+|attribution\w*|\w*noncommercial\w*|\w*sharealike|\w*noderiv\w*"
)


def _files() -> dict[str, str]:
    folder = resources.files("mediarel.llm") / "license_texts"
    return {x.name.removesuffix(".txt"): x.read_text(encoding="utf-8") for x in folder.iterdir() if x.name.endswith(".txt")}


def known_licenses() -> dict[str, tuple[str, ...]]:
    """All wordings by license: ``TEMPLATES``, notices from ``NAMES``, SPDX tags, ``TEXTS`` and the full texts."""
    made: dict[str, list[str]] = {k: [v] for k, v in TEMPLATES.items()}
    for key, names in NAMES.items():
        own = made.setdefault(key, [])
        own += [f"{lead} {name}" for name in names for lead in LEADS if name not in _BARE or lead == "under"]
        own += [f"{name} licensed" for name in names if "License" not in name]
        own += [f"SPDX-License-Identifier: {key}{x}" for x in (("", "-only", "-or-later", "+") if "gpl" in key or "gfdl" in key else ("",))]
        own += [f"SPDX-License-Identifier: {x} {op} {key}" for op in ("OR", "AND") for x in NAMES if x != key]
    for more in (TEXTS, {k: (v,) for k, v in _files().items()}):
        for key, texts in more.items():
            made.setdefault(key, []).extend(texts)
    return {k: tuple(dict.fromkeys(v)) for k, v in made.items()}


_DROPPED = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def words_of(text: str | None) -> list[bytes]:
    """Words without punctuation and case."""
    return text.encode("utf-8", "surrogatepass").lower().translate(None, _DROPPED).split() if text else []


@dataclass(frozen=True)
class Template:
    name: str
    shingles: np.ndarray
    width: int
    reach: int
    need: int
    telling: frozenset[bytes]
    notice: bool
    wanted: bytes
    barred: bytes
    bands: np.ndarray

    @property
    def least_bands(self) -> int:
        """Band values that a window with a match is asked for; it holds at least so many unless all of a long template's are missing."""
        return max(1, len(self.bands) - (len(self.shingles) - self.need))

    @property
    def miss_chance(self) -> float:
        """Bound on the chance that a match is not retrieved: that all band values are among the shingles it lacks."""
        lacking = len(self.shingles) - self.need
        return 0.0 if len(self.bands) > lacking else (lacking / len(self.shingles)) ** len(self.bands)

    def fits(self, words: list[bytes]) -> bool:
        """Whether the words of a match tell this license and no relative."""
        if self.notice:
            found = {w for w in words if _TELLING.fullmatch(w)}
            if not self.telling <= found or any(w not in self.telling and not w.lstrip(b"v").isdigit() for w in found):
                return False
        text = b" " + b" ".join(words) + b" "
        return self.wanted in text and not (self.barred and self.barred in text)


def _phrase(text: str | None) -> bytes:
    return b" " + text.encode() + b" " if text else b""


def band_minima(shingles: np.ndarray) -> np.ndarray:
    """The smallest hash of each band of the hash space that holds one."""
    ordered = np.sort(shingles.view(np.uint64))
    return ordered[np.unique(ordered >> np.uint64(64 - BAND_BITS), return_index=True)[1]].view(np.int64)


def prepare(templates: Mapping[str, str | Sequence[str]]) -> list[Template]:
    made: dict[tuple[str, tuple[bytes, ...]], Template] = {}
    for name, texts in sorted(templates.items()):
        for text in [texts] if isinstance(texts, str) else texts:
            words = words_of(text)
            if not words:
                continue
            width = min(WIDTH, len(words))
            shingles = np.unique(near_dup.rolled(near_dup.word_hashes(b" ".join(words)), width))
            # A match keeps within the template's length widened by half; all its words, if it has no more than a shingle.
            reach = len(words) - width + 1 + (len(words) // 2 if len(words) > width else 0)
            telling = frozenset(w for w in words if _TELLING.fullmatch(w))
            full = b" ".join(words)
            wanted, barred = _phrase(WANTED.get(name)), _phrase(BARRED.get(name))
            notice = len(words) <= NOTICE_WORDS
            if wanted.strip() not in full:
                wanted = b""
            need = len(shingles) if len(words) < WHOLE_WORDS else ceil(CONTAINMENT * len(shingles) - 1e-9)
            made[name, tuple(words)] = Template(name, shingles, width, reach, need, telling, notice, wanted, barred, band_minima(shingles))
    return list(made.values())


class Scanner:
    """Band values of all templates by shingle width, with the templates that have them."""

    def __init__(self, templates: Mapping[str, str | Sequence[str]]):
        self.templates = prepare(templates)
        self.index: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        for width in sorted({t.width for t in self.templates}):
            own = [k for k, t in enumerate(self.templates) if t.width == width]
            values = np.concatenate([self.templates[k].bands for k in own])
            holders = np.repeat(np.array(own), [len(self.templates[k].bands) for k in own])
            order = np.argsort(values, kind="stable")
            distinct, firsts = np.unique(values[order], return_index=True)
            slots = np.zeros(SLOTS, dtype=bool)
            slots[distinct & (SLOTS - 1)] = True
            self.index[width] = distinct, np.append(firsts, len(values)), holders[order], slots
        self.least = np.array([t.least_bands for t in self.templates])
        self.filler = np.full(WIDTH, 0x5BD1E9955BD1E995, dtype=np.uint64)

    def hits(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(template, place) of every band value of a template, in no order."""
        found = []
        for width, (distinct, firsts, holders, slots) in self.index.items():
            for block in range(0, len(hashes), BLOCK_WORDS):
                shingles = near_dup.rolled(hashes[block : block + BLOCK_WORDS + width - 1], width)
                at = np.nonzero(slots[shingles & (SLOTS - 1)])[0]
                near = np.minimum(np.searchsorted(distinct, shingles[at]), len(distinct) - 1)
                same = distinct[near] == shingles[at]
                at, near = at[same], near[same]
                counts = firsts[near + 1] - firsts[near]
                each = np.repeat(firsts[near], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
                found.append((holders[each], np.repeat(at + block, counts)))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True))

    @staticmethod
    def windows(template: Template, places: np.ndarray) -> list[tuple[int, int]]:
        """Merged overlapping windows [first, end) of a text that hold enough band values at these places, in order."""
        slot, held = np.unique(places // template.reach, return_counts=True)
        counts = dict(zip(slot.tolist(), held.tolist(), strict=True))
        out: list[list[int]] = []
        for w in sorted({x for s in counts for x in (s - 1, s) if x >= 0} | {0}):
            if counts.get(w, 0) + counts.get(w + 1, 0) >= template.least_bands:
                first, end = w * template.reach, (w + 2) * template.reach
                if out and first <= out[-1][1]:
                    out[-1][1] = end
                else:
                    out.append([first, end])
        return [(a, b) for a, b in out]

    def stretches(self, template: Template, places: list[int], values: list[int]) -> list[list]:
        """[first, end, distinct shingles] of the merged stretches within reach that hold enough of the template."""
        held: Counter[int] = Counter()
        out: list[list] = []
        left = 0
        for place, value in zip(places, values, strict=True):
            held[value] += 1
            while place - places[left] >= template.reach or held[values[left]] > 1 and places[left] < place:
                held[values[left]] -= 1
                if not held[values[left]]:
                    del held[values[left]]
                left += 1
            if len(held) >= template.need:
                first, end = places[left], place + template.width
                if out and first < out[-1][1]:
                    out[-1][1], out[-1][2] = end, max(len(held), out[-1][2])
                else:
                    out.append([first, end, len(held)])
        return out

    def scan(self, texts: list[str | None]) -> list[list[tuple[str, int, int, float]]]:
        """For each text (license, first word, end word, containment) of every span, in order of license and place.

        Texts stand in one array with filler between them, so short texts share the cost of a pass.
        """
        parts, firsts, at, held = [], [], 0, []
        for text in texts:
            held.append(words_of(text))
            firsts.append(at)
            parts += [near_dup.word_hashes(b" ".join(held[-1])), self.filler]
            at += len(held[-1]) + WIDTH
        rows: list[list[tuple[str, int, int, float]]] = [[] for _ in texts]
        if not self.templates or not any(held):
            return rows
        hashes = np.concatenate(parts)
        owner, place = self.hits(hashes)
        text_of = np.searchsorted(np.array(firsts), place, side="right") - 1
        order = np.lexsort((place, owner, text_of))
        owner, place, text_of = owner[order], place[order], text_of[order]
        starts = np.nonzero(np.append(True, (np.diff(owner) != 0) | (np.diff(text_of) != 0)))[0] if len(owner) else np.empty(0, dtype=np.int64)
        ends = np.append(starts[1:], len(owner))
        enough = ends - starts >= self.least[owner[starts]]
        spans: dict[int, dict[str, list[tuple[int, int, float]]]] = {}
        for a, b in zip(starts[enough].tolist(), ends[enough].tolist(), strict=True):
            template, own = self.templates[owner[a]], int(text_of[a])
            for low, high in self.windows(template, place[a:b] - firsts[own]):
                # The exact shingles of the window, wherever its band values stood.
                inside = near_dup.rolled(hashes[firsts[own] + low : firsts[own] + min(high + template.width - 1, len(held[own]))], template.width)
                near = np.minimum(np.searchsorted(template.shingles, inside), len(template.shingles) - 1)
                at = np.nonzero(template.shingles[near] == inside)[0]
                for first, end, n in self.stretches(template, (at + low).tolist(), near[at].tolist()):
                    if template.fits(held[own][first:end]):
                        spans.setdefault(own, {}).setdefault(template.name, []).append((first, end, n / len(template.shingles)))
        for own, by_name in spans.items():
            for name, found in sorted(by_name.items()):
                merged: list[list] = []
                for first, end, share in sorted(found):
                    if merged and first < merged[-1][1]:
                        merged[-1][1], merged[-1][2] = max(end, merged[-1][1]), max(share, merged[-1][2])
                    else:
                        merged.append([first, end, share])
                rows[own] += [(name, *m) for m in merged]
        return rows


def _blocks(texts: list[str | None], most_chars: int = 1 << 20) -> Iterator[tuple[int, int]]:
    start = held = 0
    for i, text in enumerate(texts):
        held += len(text or "")
        if held >= most_chars:
            yield start, i + 1
            start, held = i + 1, 0
    if start < len(texts):
        yield start, len(texts)


def scan(docs: DataFrame, templates: Mapping[str, str | Sequence[str]] | None = None) -> DataFrame:
    """doc_id, license, first_word, end_word, containment: one row for each span of a license in a text."""
    templates = known_licenses() if templates is None else dict(templates)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.claim("words")
        scanner = Scanner(templates)
        for part in common.slices(batches, 128):
            ids, texts = part.column(0), part.column(1).to_pylist()
            rows = [(a + i, *m) for a, b in _blocks(texts) for i, found in enumerate(scanner.scan(texts[a:b])) for m in found]
            fields = [pa.array([r[k] for r in rows], kind) for k, kind in enumerate((pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64()))]
            yield pa.RecordBatch.from_arrays([ids.take(fields[0]), *fields[1:]], names=["doc_id", "license", "first_word", "end_word", "containment"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, license string, first_word long, end_word long, containment double")


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(common.table(spark, sf_dir, "documents"))
