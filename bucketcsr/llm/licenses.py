"""Licence scans through a positional index of rare licence words.

Template words get an inverse document frequency over the templates, and an index lists where each word stands in which template (a fixed
table that goes along with the function). For a text, only templates that could match at all are looked at: the words that it
shares with a template must carry `share` of the template's weight. For each of these the text's `rare` licence words of highest
frequency rank are looked up; each occurrence votes for a place of the template's first word. Places where at least half of those
words agree, give or take `slack` words, are compared with the whole template, and count only if all of the template's
mandatory key phrases stand inside. One Arrow pass, no shuffle, nothing grows with the corpus.

Base labels come from three phrases wherever their words stand consecutively; the index adds labels of its own.
Null text: empty, no labels (empty strings), null places. Repeated rows and extra columns: carried along.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame, types as T

from .shared import map_text

#: Phrases that the contract names, and their labels.
BASE_PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}

#: Label, public licence wording, key phrases that must all occur.
TEMPLATES = [
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction", ["permission is hereby granted free of charge", "without restriction"]),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement", ["this permission notice shall be included in all copies or substantial portions of the software"]),
    ("mit", "licensed under the terms of the mit license", ["mit license"]),
    ("mit", "spdx license identifier mit", ["spdx license identifier mit"]),
    ("apache-2", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", ["apache license version 2 0"]),
    ("apache-2", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license", ["see the license for the specific language governing permissions and limitations under the license"]),
    ("apache-2", "spdx license identifier apache 2 0", ["spdx license identifier apache 2 0"]),
    ("gpl-3", "licensed under the gnu general public license version 3", ["gnu general public license version 3"]),
    ("gpl-3", "under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version", ["gnu general public license", "version 3 of the license"]),
    ("gpl-3", "spdx license identifier gpl 3 0", ["spdx license identifier gpl 3 0"]),
    ("gpl-2", "licensed under the gnu general public license version 2", ["gnu general public license version 2"]),
    ("gpl-2", "under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version", ["gnu general public license", "version 2 of the license"]),
    ("gpl-2", "spdx license identifier gpl 2 0", ["spdx license identifier gpl 2 0"]),
    ("lgpl", "under the terms of the gnu lesser general public license as published by the free software foundation", ["gnu lesser general public license"]),
    ("agpl-3", "under the terms of the gnu affero general public license as published by the free software foundation", ["gnu affero general public license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ["redistribution and use in source and binary forms"]),
    ("bsd", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", ["may be used to endorse or promote products derived from this software"]),
    ("bsd", "use of this source code is governed by a bsd style license that can be found in the license file", ["bsd style license"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["with or without fee is hereby granted"]),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license v 2 0"]),
    ("epl-2", "this program and the accompanying materials are made available under the terms of the eclipse public license", ["eclipse public license"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["unencumbered software released into the public domain"]),
    ("boost-1", "distributed under the boost software license version 1 0", ["boost software license version 1 0"]),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", ["in no event will the authors be held liable"]),
    ("cc0-1", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work cc0 1 0 universal", ["waived all copyright and related or neighboring rights"]),
    ("cc-by", "licensed under the creative commons attribution 4 0 international license", ["creative commons attribution 4 0 international"]),
    ("cc-by-sa", "licensed under the creative commons attribution sharealike 4 0 international license", ["creative commons attribution sharealike"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc-by-nc", "licensed under the creative commons attribution noncommercial 4 0 international license", ["creative commons attribution noncommercial"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
]

#: Lower-cases A-Z and blanks every ASCII byte that is no letter or digit.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


class LicenseIndex:
    """Positions of all template words.

    rare: a file's words looked up per template, rarest first; share: least idf-weighted part of a template that a match must hold.
    """

    def __init__(self, templates=TEMPLATES, rare: int = 6, share: float = 0.6, slack: int = 3) -> None:
        self.share, self.slack, self.rare = share, slack, rare
        self.labels = [t[0] for t in templates]
        self.words = [t[1].encode().split() for t in templates]
        self.phrases = [[b" " + p.encode() + b" " for p in t[2]] for t in templates]
        df = Counter(w for words in self.words for w in set(words))
        self.idf = {w: math.log((1 + len(templates)) / n) for w, n in df.items()}
        self.postings: list[dict[bytes, list[int]]] = []
        for words in self.words:
            at: dict[bytes, list[int]] = defaultdict(list)
            for pos, w in enumerate(words):
                at[w].append(pos)
            self.postings.append(dict(at))
        self.ranked = [sorted(at, key=lambda w: (-self.idf[w], w)) for at in self.postings]
        self.total = [sum(self.idf[w] for w in words) for words in self.words]
        self.vocabulary = frozenset(self.idf)

    def candidates(self, present: frozenset[bytes]) -> list[int]:
        """Templates of whose weight the present words carry the share."""
        found = []
        for t, at in enumerate(self.postings):
            lost = (1 - self.share) * self.total[t]
            for w in self.ranked[t]:
                if w not in present:
                    lost -= self.idf[w] * len(at[w])
                    if lost < -1e-9:
                        break
            else:
                found.append(t)
        return found

    def matches(self, words: list[bytes]) -> dict[str, float]:
        """Label -> best share of a template found in the words."""
        present = self.vocabulary.intersection(words)
        if not present or not (among := self.candidates(present)):
            return {}
        chosen = {t: [w for w in self.ranked[t] if w in present][: self.rare] for t in among}
        wanted = {w for some in chosen.values() for w in some}
        where: dict[bytes, list[int]] = defaultdict(list)
        for at, w in enumerate(words):
            if w in wanted:
                where[w].append(at)
        found: dict[str, float] = {}
        for t in among:
            votes: dict[int, set[bytes]] = defaultdict(set)
            for w in chosen[t]:
                for pos in self.postings[t][w]:
                    for at in where[w]:
                        votes[at - pos].add(w)
            need = max(1, (len(chosen[t]) + 1) // 2)
            for begin, seen in votes.items():
                near = seen.union(*(votes.get(begin + d, ()) for d in range(-self.slack, self.slack + 1) if d))
                if len(near) >= need and (share := self._verify(t, begin, words)) >= self.share:
                    found[self.labels[t]] = max(found.get(self.labels[t], 0.0), share)
        return found

    def _verify(self, t: int, begin: int, words: list[bytes]) -> float:
        """The template's weighted share that stands at the place, or 0 if a key phrase is missing."""
        template = self.words[t]
        lo = max(0, begin - self.slack)
        span = words[lo : max(0, begin + len(template) + self.slack)]
        text = b" " + b" ".join(span) + b" "
        if not all(p in text for p in self.phrases[t]):
            return 0.0
        got = 0.0
        for k, w in enumerate(template):
            here = begin + k - lo
            if w in span[max(0, here - self.slack) : max(0, here + self.slack + 1)]:
                got += self.idf[w]
        return got / self.total[t]


def places(joined: bytes, phrase: bytes) -> list[int]:
    """Word numbers at which the phrase's words stand in the words joined by single spaces, framed by spaces."""
    out, at, word, last = [], joined.find(phrase), 0, 0
    while at >= 0:
        word += joined.count(b" ", last, at)
        last = at
        out.append(word)
        at = joined.find(phrase, at + 1)
    return out


def scan(docs: DataFrame, text: str = "text", keep: list[str] | None = None, index: LicenseIndex | None = None) -> DataFrame:
    """keep columns (default: all of docs) + n_words, n_base, first_word, last_word, base_labels, labels, score."""
    added = [("n_words", T.LongType()), ("n_base", T.LongType()), ("first_word", T.LongType()), ("last_word", T.LongType()), ("base_labels", T.StringType()), ("labels", T.StringType()), ("score", T.DoubleType())]
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in {a for a, _ in added}]
    index = index or LicenseIndex()
    base = [(b" " + p.encode() + b" ", label) for p, label in BASE_PHRASES.items()]
    maybe = re.compile(b"|".join(re.escape(p.strip()) for p, _ in base))

    def make(texts: pa.Array) -> list[pa.Array]:
        cols: list[list] = [[] for _ in added]
        for raw in texts.cast(pa.large_binary()).to_pylist():
            words = (raw or b"").translate(FOLD).split()
            at: list[int] = []
            labels: set[str] = set()
            joined = b" " + b" ".join(words) + b" "
            if maybe.search(joined):
                for phrase, label in base:
                    if found := places(joined, phrase):
                        at += found
                        labels.add(label)
            more = index.matches(words)
            row = (len(words), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels)), ",".join(sorted(labels | more.keys())), 1.0 if labels else max(more.values(), default=0.0))
            for col, x in zip(cols, row, strict=True):
                col.append(x)
        kinds = {T.LongType: pa.int64(), T.StringType: pa.string(), T.DoubleType: pa.float64()}
        return [pa.array(col, kinds[type(t)]) for col, (_, t) in zip(cols, added, strict=True)]

    return map_text(docs, text, [T.StructField(n, t) for n, t in added], make, keep)
