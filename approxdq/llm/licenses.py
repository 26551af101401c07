"""Licence notices: exact phrases, and short notices found with a bounded number of edits.

A text is lower-cased (A-Z) and reduced to its words joined by one space. A notice of m bytes that
may differ by e edits is split into e + 1 parts: whatever the edits, one part stands there unchanged
(pigeonhole). One automaton over the parts of all notices finds the places; around each, the regex
library matches the notice with at most e errors and reports span and edits.

Null and empty texts have no words, no labels and score 0. Ties of overlapping matches: fewer edits,
then the earlier one. Very long texts are scanned whole; memory follows the longest text.
"""

from __future__ import annotations

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import common as C

# Phrases of the base search and their labels.
PHRASES = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))
# Short notices of the fuzzy search and their labels.
NOTICES = (
    ("under the mit license", "mit"),
    ("apache license version 2", "apache-2"),
    ("cc by nc", "cc-by-nc"),
    ("permission is hereby granted free of charge to any person obtaining a copy", "mit"),
    ("gnu general public license", "gpl"),
    ("gnu lesser general public license", "lgpl"),
    ("mozilla public license", "mpl"),
    ("redistribution and use in source and binary forms", "bsd"),
    ("permission to use copy modify and or distribute this software", "isc"),
    ("creative commons attribution", "cc-by"),
    ("eclipse public license", "epl"),
    ("the above copyright notice and this permission notice shall be included in all copies", "mit"),
    ("licensed under the apache license", "apache-2"),
    ("apache software foundation license", "apache"),
    ("redistributions of source code must retain the above copyright notice", "bsd"),
    ("redistributions in binary form must reproduce the above copyright notice", "bsd"),
    ("gnu affero general public license", "agpl"),
    ("gnu free documentation license", "gfdl"),
    ("boost software license", "bsl"),
    ("artistic license", "artistic"),
    ("academic free license", "afl"),
    ("open software license", "osl"),
    ("common development and distribution license", "cddl"),
    ("european union public licence", "eupl"),
    ("microsoft public license", "ms-pl"),
    ("sil open font license", "ofl"),
    ("python software foundation license", "psf"),
    ("creative commons zero", "cc0"),
    ("cc0 1 0 universal", "cc0"),
    ("this software is provided as is without any express or implied warranty in no event will the authors be held liable", "zlib"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
)
_WORDS = bytes(C.LOWER[b] if C.IS_WORD[C.LOWER[b]] else 32 for b in range(256))


def edits_for(notice: str, per: int = 10) -> int:
    """Edits allowed: one for each ten characters; none in notices too short for it."""
    return len(notice) // per


class NoticeSearch:
    def __init__(self, phrases=PHRASES, notices=NOTICES, edits=edits_for):
        self.phrases = [(b" " + p.encode() + b" ", label) for p, label in phrases]
        self.notices, parts = [], {}
        for k, (notice, label) in enumerate(notices):
            e, m = edits(notice), len(notice)
            self.notices.append((notice, label, e, regex.compile(rf"(?e)(?<![^ ])(?:{regex.escape(notice, literal_spaces=True)}){{e<={e}}}(?![^ ])")))
            cuts = [m * i // (e + 1) for i in range(e + 2)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                parts.setdefault(notice[a:b], []).append((k, a, b - a))
        self.seeds = ahocorasick.Automaton()
        for part, uses in parts.items():
            self.seeds.add_word(part, uses)
        self.seeds.make_automaton()

    def spans(self, norm: str) -> list[tuple[int, int, str, int, int]]:
        """(start, end, label, edits, length of the notice) of every verified place; Latin-1 text of words joined by a space."""
        areas: dict[int, list[list[int]]] = {}
        for end, uses in self.seeds.iter(norm):
            for k, at, size in uses:
                notice, e = self.notices[k][0], self.notices[k][2]
                lo = max(0, end - size + 1 - at - e)
                hi = min(len(norm), lo + len(notice) + 2 * e + 1)
                seen = areas.setdefault(k, [])
                if seen and lo <= seen[-1][1] and lo >= seen[-1][0]:
                    seen[-1][1] = max(seen[-1][1], hi)
                else:
                    seen.append([lo, hi])
        found = set()
        for k, seen in areas.items():
            notice, label, e, pattern = self.notices[k]
            for lo, hi in seen:
                for m in pattern.finditer(norm, lo, min(len(norm), hi + 1)):
                    found.add((m.start(), m.end(), label, sum(m.fuzzy_counts), len(notice)))
        return sorted(found, key=lambda x: (x[0], x[3], x[1], x[2]))

    def scan(self, text: bytes):
        """Words, base places as (word, label), fuzzy spans of one text."""
        words = text.translate(_WORDS).split()
        if not words:
            return 0, [], []
        norm = b" ".join(words)
        padded, places = b" " + norm + b" ", []
        for phrase, label in self.phrases:
            at, last, word = padded.find(phrase), 0, 0
            while at >= 0:
                word += padded.count(b" ", last, at)
                places.append((word, label))
                at, last = padded.find(phrase, at + 1), at
        return len(words), places, self.spans(norm.decode("latin-1"))


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<start:long,end:long,label:string,edits:int>>"
_ARROW = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("label", pa.string()), ("edits", pa.int32())])))])


def license_notices(docs: DataFrame, phrases=PHRASES, notices=NOTICES) -> DataFrame:
    """One row per document. spans: fuzzy matches, as byte places in the words joined by one space;
    score: 1 for an exact phrase, else the best match's share of unedited characters, 0 without any."""

    def run(batches):
        search = NoticeSearch(phrases, notices)
        for batch in batches:
            for piece in C.pieces(batch):
                data, offs = C.flat(piece.column("text"))
                body, rows = data.tobytes(), {n: [] for n in _ARROW.names}
                for i in range(piece.num_rows):
                    n, base, spans = search.scan(body[offs[i] : offs[i + 1]])
                    own = sorted({label for _, label in base})
                    at = [w for w, _ in base]
                    rows["n_words"].append(n)
                    rows["n_base"].append(len(base))
                    rows["first_word"].append(min(at) if at else None)
                    rows["last_word"].append(max(at) if at else None)
                    rows["base_labels"].append(",".join(own))
                    rows["labels"].append(",".join(sorted({*own, *(s[2] for s in spans)})))
                    rows["score"].append(1.0 if base else max((max(0.0, 1 - s[3] / s[4]) for s in spans), default=0.0))
                    rows["spans"].append([{"start": s[0], "end": s[1], "label": s[2], "edits": s[3]} for s in spans])
                rows["doc_id"] = piece.column("doc_id")
                yield pa.RecordBatch.from_arrays([x if isinstance(x := rows[f.name], pa.Array) else pa.array(x, f.type) for f in _ARROW], schema=_ARROW)

    return C.documents(docs).mapInArrow(run, SCHEMA)
