"""Token counts by section, from one encoding of the whole document.

A document is encoded once, so tokens are those of the real text, and each token's character span
follows from the bytes it stands for. Sections tile the text (by default: lines, each with its line
break). Spans and sections are both in order, so their interval join is one merge (a search of the
sorted section ends). A token that crosses a border goes by an explicit rule:

- ``first``: to the section that holds its first character;
- ``most``: to the section that holds most of its characters, ties to the earlier one;
- ``split``: to each section by its share of the characters.

A token that holds part of a character belongs to the place of that character. Null and empty texts
have one empty section 0 with no tokens. Sections always add up to the document's tokens.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C
from .bpe import encoder

RULES = ("first", "most", "split")


def line_borders(text: str) -> np.ndarray:
    """Ends of the lines of a text, in characters; the last is the length."""
    points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    ends = np.flatnonzero(points == 10) + 1
    return ends if len(ends) and ends[-1] == len(points) else np.append(ends, len(points))


def token_spans(text: str, ids, token: dict[int, bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Characters [start, end) of each token; a part of a character has that character's place."""
    data = np.frombuffer(text.encode(), np.uint8)
    char = np.cumsum((data & 0xC0) != 0x80) - 1
    ends = np.cumsum([len(token[i]) for i in ids], dtype=np.int64)
    starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
    return (char[starts], char[ends - 1] + 1) if len(ends) else (starts[:0], ends)


def attribute(starts: np.ndarray, ends: np.ndarray, borders: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each section, and how many of its tokens cross its end."""
    n = len(borders)
    first, last = np.searchsorted(borders, starts, "right"), np.searchsorted(borders, ends - 1, "right")
    crossing = np.bincount(first[first != last], minlength=n)
    if rule == "first":
        return np.bincount(first, minlength=n).astype(float), crossing
    counts = np.bincount(first[first == last], minlength=n).astype(float)
    for k in np.flatnonzero(first != last):
        edges = np.concatenate([[starts[k]], borders[first[k] : last[k]], [ends[k]]])
        parts = np.diff(edges)
        if rule == "most":
            counts[first[k] + int(parts.argmax())] += 1
        else:
            counts[first[k] : last[k] + 1] += parts / parts.sum()
    return counts, crossing


_ARROW = pa.schema([("doc_id", pa.int64()), ("section", pa.int64()), ("char_start", pa.int64()), ("char_end", pa.int64()), ("n_tokens", pa.float64()), ("n_crossing", pa.int64())])
SCHEMA = "doc_id long, section long, char_start long, char_end long, n_tokens double, n_crossing long"


def tokens_by_section(docs: DataFrame, path: str, pattern: str, rule: str = "first", borders=line_borders) -> DataFrame:
    """One row per section of each document: its characters, its tokens, and those that cross its end."""
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        enc, parts = encoder(path, pattern), []
        for doc, text in zip(piece.column("doc_id").to_pylist(), piece.column("text").to_pylist(), strict=True):
            text = text or ""
            edges = borders(text)
            counts, crossing = attribute(*token_spans(text, enc.encode(text), enc.token), edges, rule)
            parts.append((doc, edges, counts, crossing))
        sizes = [len(p[1]) for p in parts]
        join = lambda xs, kind: pa.array(np.concatenate([*xs, np.zeros(0, kind)]).astype(kind))
        ids = pa.array([p[0] for p in parts], pa.int64()).take(pa.array(np.repeat(np.arange(len(parts)), sizes)))
        return pa.RecordBatch.from_arrays([ids, join([np.arange(n) for n in sizes], np.int64), join([np.append(0, p[1][:-1]) for p in parts], np.int64), join([p[1] for p in parts], np.int64), join([p[2] for p in parts], float), join([p[3] for p in parts], np.int64)], schema=_ARROW)

    return C.map_pieces(C.documents(docs), work, SCHEMA, done=lambda: encoder(path, pattern).trim())


def tokens_by_document(sections: DataFrame) -> DataFrame:
    return sections.groupBy("doc_id").agg(F.sum("n_tokens").alias("n_tokens"), F.count(F.lit(1)).alias("n_sections"), F.sum("n_crossing").alias("n_crossing"))
