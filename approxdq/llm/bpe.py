"""Byte-level BPE: encode by backtracking over longest matches, decode by look-up.

Bytes are read as Latin-1 characters, so one automaton over all tokens finds every token that starts
at each byte. The encoder takes the longest; a token may follow another only if the merge rules would
leave the two apart, which is decided once per pair and remembered. If none fits, it steps back one
token and bars the place, so each byte is barred once at most and the work stays linear. The outcome
is that of merging by rank. Pieces that are themselves tokens are looked up, as the public library does.

Null and empty texts have no tokens. Any text is whole; memory follows the longest one.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Callable
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import common as C

#: Pieces whose ids a worker remembers at most, those that stay when it is full or a task ends (the ones seen first, among
#: which the frequent ones are), and pairs of tokens. They bound memory and change no result.
REMEMBER, KEEP, PAIRS = 800_000, 500_000, 300_000


class Remembered(dict):
    """Ids of pieces, encoded when they are first asked for."""

    def __init__(self, encode: Callable[[bytes], tuple[int, ...]]):
        self.encode = encode

    def __missing__(self, piece: str) -> tuple[int, ...]:
        ids = self.encode(piece.encode())
        if len(piece) < 64:
            if len(self) >= REMEMBER:
                self.trim()
            self[piece] = ids
        return ids

    def trim(self) -> None:
        for late in list(self)[KEEP:]:
            del self[late]


class ByteEncoder:
    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            self.rank = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.token = {i: t for t, i in self.rank.items()}
        self.length = {i: len(t) for t, i in self.rank.items()}
        self.text_of_id = {i: b"%d" % i for i in self.token}
        self.split_pieces = regex.compile(pattern).findall
        self.shorter: dict[int, int] = {}  # the longest token that is a proper prefix
        for t, i in self.rank.items():
            for n in range(len(t) - 1, 0, -1):
                if (j := self.rank.get(t[:n])) is not None:
                    self.shorter[i] = j
                    break
        self.merged: dict[tuple[int, int], int] = {}
        self.halves: dict[int, tuple[int, int]] = {}
        self.fits: dict[tuple[int, int], bool] = {}
        for i in sorted(self.token):
            self.halves[i] = (i, i)
            left = self.shorter.get(i)
            while left is not None:
                right = self.rank.get(self.token[i][len(self.token[left]) :])
                if right is not None and left < i and right < i and self._apart(left, right):
                    self.merged[left, right], self.halves[i] = i, (left, right)
                    break
                left = self.shorter.get(left)
        self.tokens_in = ahocorasick.Automaton()
        for t, i in self.rank.items():
            self.tokens_in.add_word(t.decode("latin-1"), (len(t) - 1, i))
        self.tokens_in.make_automaton()
        self.cache = Remembered(self.encode_piece)

    def _apart(self, a: int, b: int) -> bool:
        """Whether merging by rank leaves a and b as neighbours: undo their merges from the latest on, and
        look for a merge across the border that would have come first."""
        bar = 1 << 60
        while True:
            if self.merged.get((a, b), bar) < bar:
                return False
            from_left = a > b
            for _ in range(2):
                if from_left:
                    bar, a = a, self.halves[a][1]
                    if a != bar:
                        break
                else:
                    bar, b = b + 1, self.halves[b][0]
                    if b + 1 != bar:
                        break
                from_left = not from_left
            else:
                return True

    def encode_piece(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one piece."""
        if (i := self.rank.get(piece)) is not None:
            return (i,)
        size = len(piece)
        longest = [0] * size
        for end, (back, i) in self.tokens_in.iter(piece.decode("latin-1")):
            longest[end - back] = i  # a later end is a longer token
        barred, out, at, fits, length = bytearray(size + 1), [], 0, self.fits, self.length
        now = longest[0] if size else None
        while now is not None:
            last = out[-1] if out else None
            while now is not None:
                to = at + length[now]
                if not barred[to]:
                    if last is None:
                        break
                    ok = fits.get((last, now))
                    if ok is None:
                        ok = fits[last, now] = self._apart(last, now)
                    if ok:
                        break
                now = self.shorter.get(now)
            if now is not None:
                out.append(now)
                at, now = to, longest[to] if to < size else None
            else:
                barred[at] = 1
                now = out.pop()
                at -= length[now]
        if len(fits) > PAIRS:
            fits.clear()
        return tuple(out)

    def trim(self) -> None:
        """Forgets all but the first pieces."""
        self.cache.trim()

    def encode_pieces(self, text: str) -> list[tuple[int, ...]]:
        """Ids of each piece of a text, in order."""
        return list(map(self.cache.__getitem__, self.split_pieces(text)))

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(self.encode_pieces(text)))

    def decode(self, ids) -> bytes:
        return b"".join(map(self.token.__getitem__, ids))


_MADE: dict[tuple[str, str], ByteEncoder] = {}


def encoder(path: str, pattern: str) -> ByteEncoder:
    """One encoder for each worker process."""
    if (path, pattern) not in _MADE:
        _MADE[path, pattern] = ByteEncoder(path, pattern)
    return _MADE[path, pattern]


SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, same_bytes boolean"
_ARROW = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string()), ("same_bytes", pa.bool_())])


def encode_documents(docs: DataFrame, path: str, pattern: str, ids: bool = False) -> DataFrame:
    """One row per document: counts and digests of ids and of what decoding gives; with ``ids``, the ids too."""
    schema = _ARROW.append(pa.field("ids", pa.list_(pa.int32()))) if ids else _ARROW

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        enc = encoder(path, pattern)
        n, sha, back, same, kept = [], [], [], [], []
        for text in piece.column("text").to_pylist():
            own = enc.encode(text or "")
            whole = enc.decode(own)
            n.append(len(own))
            sha.append(hashlib.sha256(b",".join(map(enc.text_of_id.__getitem__, own))).hexdigest())
            back.append(hashlib.sha256(whole).hexdigest())
            same.append(whole == (text or "").encode())
            if ids:
                kept.append(np.array(own, np.int32))
        columns = [piece.column("doc_id"), pa.array(n, pa.int64()), pa.array(sha), pa.array(back), pa.array(same)]
        return pa.RecordBatch.from_arrays(columns + [pa.array(kept, pa.list_(pa.int32()))] * ids, schema=schema)

    return C.map_pieces(C.documents(docs), work, SCHEMA + ", ids array<int>" * ids, done=lambda: encoder(path, pattern).trim())
