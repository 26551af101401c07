"""Suffix and common-prefix arrays by external induced sorting.

The text is bytes 1..255 in which 0 ends an item; it may be a memory map. Suffix tuples
(position, common prefix with the tuple before) wait in a priority queue ordered by first byte and
arrival; its queues go to disk beyond a memory limit and come back block by block. The suffixes that start
a rising slope (S*) are ordered first. Going up through the queue they induce the suffixes of falling
slopes, going down those induce the suffixes of rising slopes, and each induced tuple gets its common
prefix as one more than the least one passed since the last tuple of its queue.

S* suffixes are ordered by recursion on ties: each level compares the next eight bytes of those that the levels
before left equal, until ``depth`` bytes. So arrays hold to ``depth``: suffixes that agree on ``depth`` bytes
may stand in any order, and common prefixes are cut there. A full array has depth = len(text).
"""

from __future__ import annotations

import os
import tempfile

import numpy as np

_TUPLE = np.dtype([("at", np.int64), ("lcp", np.int32)])


class ByteQueues:
    """A priority queue of suffix tuples by first byte, then arrival; spills to disk beyond ``limit`` tuples."""

    def __init__(self, limit: int, folder: str):
        self.limit, self.folder = limit, folder
        self.waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
        self.held, self.spilled = 0, [False] * 256

    def _file(self, byte: int) -> str:
        return os.path.join(self.folder, f"{byte}.tuples")

    def push(self, byte: int, tuples: np.ndarray) -> None:
        self.waiting[byte].append(tuples)
        self.held += len(tuples)
        if self.held > self.limit:
            for b, blocks in enumerate(self.waiting):
                if blocks:
                    with open(self._file(b), "ab") as f:
                        for block in blocks:
                            f.write(block.tobytes())
                    self.waiting[b], self.spilled[b] = [], True
            self.held = 0

    def pop(self, byte: int, most: int):
        """Blocks of the tuples that wait for this byte, in their order; those pushed meanwhile are left."""
        blocks, self.waiting[byte] = self.waiting[byte], []
        self.held -= sum(map(len, blocks))
        if self.spilled[byte]:
            name, self.spilled[byte] = self._file(byte) + ".now", False
            os.rename(self._file(byte), name)
            with open(name, "rb") as f:
                while body := f.read(most * _TUPLE.itemsize):
                    yield np.frombuffer(body, _TUPLE)
            os.unlink(name)
        if blocks:
            whole = np.concatenate(blocks)
            for k in range(0, len(whole), most):
                yield whole[k : k + most]


def _least(values: np.ndarray):
    """A function (from, to) -> least of values[from:to] for arrays of non-empty ranges."""
    levels = [values]
    while 2 ** len(levels) <= len(values):
        below, half = levels[-1], 2 ** (len(levels) - 1)
        levels.append(np.minimum(below[:-half], below[half:]))

    def least(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        level = np.frexp((b - a).astype(float))[1] - 1
        out = np.empty(len(a), values.dtype)
        for k in np.unique(level):
            m = level == k
            out[m] = np.minimum(levels[k][a[m]], levels[k][b[m] - (1 << int(k))])
        return out

    return least


def _words(text: np.ndarray) -> np.ndarray:
    """Eight bytes from each position as one big-endian number, without a copy; text ends with eight zeros."""
    return np.ndarray((len(text) - 7,), ">u8", buffer=text, strides=(1,))


def _common(x: np.ndarray) -> np.ndarray:
    """Equal leading bytes of two words, from their exclusive or."""
    out = np.full(len(x), 8, np.int32)
    for k in range(8):
        out[(out == 8) & ((x >> np.uint64(56 - 8 * k)) & np.uint64(255) > 0)] = k
    return out


def order_starts(words: np.ndarray, starts: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """S* suffixes in order, and the common prefix of each with the one before."""
    order = np.array(starts)
    lcp = np.zeros(len(order), np.int32)
    tied = np.arange(len(order))  # places whose order is open, group after group
    group = np.zeros(len(order), np.int64)
    for done in range(0, depth, 8):
        if not len(tied):
            break
        at = order[tied]
        key = words[np.minimum(at + done, len(words) - 1)].astype(np.uint64)
        by = np.lexsort((key, group)) if done else np.argsort(key, kind="stable")
        order[tied], key, group = at[by], key[by], group[by]
        same = np.zeros(len(tied), bool)
        same[1:] = group[1:] == group[:-1]
        shared = np.zeros(len(tied), np.int32)
        shared[1:] = _common(key[1:] ^ key[:-1])
        lcp[tied[same]] = done + shared[same]
        equal = same & (shared == 8)
        group = np.cumsum(~equal)
        more = equal | np.append(equal[1:], False)
        tied, group = tied[more], group[more]
    return order, np.minimum(lcp, depth)


def induce(text: np.ndarray, depth: int, limit: int = 1 << 22, block: int = 1 << 18):
    """Yields blocks (positions, common prefixes) of the suffix array of text, whose last byte is 0."""
    n = len(text)
    padded = np.concatenate([text, np.zeros(8, np.uint8)])
    words = _words(padded)
    differs = np.flatnonzero(text[1:] != text[:-1])
    rising = np.zeros(n, bool)  # S type: the next different byte is larger
    if len(differs):
        runs = np.diff(np.concatenate([[-1], differs]))
        rising[: differs[-1] + 1] = np.repeat(text[differs + 1] > text[differs], runs)
    starts = np.flatnonzero(rising[1:] & ~rising[:-1]) + 1
    seeds, seed_lcp = order_starts(words, starts, depth)
    bounds = np.searchsorted(text[seeds], np.arange(257))

    def common(a: int, b: int) -> int:
        x, y = padded[a : a + depth], padded[b : b + depth]
        m = min(len(x), len(y))
        unequal = np.flatnonzero(x[:m] != y[:m])
        return int(unequal[0]) if len(unequal) else m

    with tempfile.TemporaryDirectory() as folder:
        for d in ("falling", "rising", "kept"):
            os.mkdir(os.path.join(folder, d))
        queue = ByteQueues(limit, os.path.join(folder, "falling"))
        since = np.full(256, depth, np.int32)  # least common prefix passed since the last tuple of each byte

        def pass_on(at: np.ndarray, lcp: np.ndarray, take) -> None:
            """Induces from a block of tuples in their order; take(first byte of the induced, of the inducing) selects."""
            inner = at > 0
            before = np.where(inner, text[np.maximum(at - 1, 0)], 0)
            chosen = np.flatnonzero(inner & take(before, text[at]))
            np.minimum(since, lcp.min(), out=since_all) if len(lcp) else None
            if len(chosen):
                least = _least(lcp)
                chosen = chosen[np.argsort(before[chosen], kind="stable")]
                byte = before[chosen]
                first = np.ones(len(chosen), bool)
                first[1:] = byte[1:] != byte[:-1]
                low = np.where(first, 0, np.append(0, chosen[:-1]) + 1)
                got = least(low, chosen + 1)
                got[first] = np.minimum(got[first], since[byte[first]])
                tuples = np.empty(len(chosen), _TUPLE)
                tuples["at"], tuples["lcp"] = at[chosen] - 1, np.minimum(got + 1, depth)
                cuts = np.append(np.flatnonzero(first), len(chosen))
                for a, b in zip(cuts, cuts[1:], strict=False):
                    queue.push(int(byte[a]), tuples[a:b])
                ends = chosen[cuts[1:] - 1] + 1
                rest = np.full(len(ends), depth, np.int32)
                more = ends < len(lcp)
                if more.any():
                    rest[more] = least(ends[more], np.full(int(more.sum()), len(lcp)))
                since_all[byte[cuts[:-1]]] = rest
            since[:] = since_all

        since_all = since.copy()

        def drain(byte: int, take, keep: ByteQueues, fresh: set[int]):
            """All rounds of a byte's queue; an induced tuple of the same byte comes in a later round."""
            while True:
                some = False
                for tuples in queue.pop(byte, block):
                    some = True
                    lcp = tuples["lcp"].copy()
                    if byte not in fresh:  # first of its byte: nothing in common with the byte before
                        lcp[0] = 0
                        fresh.add(byte)
                    kept = tuples.copy()
                    kept["lcp"] = lcp
                    keep.push(byte, kept)
                    last[0] = int(tuples["at"][-1])
                    pass_on(tuples["at"], lcp, take)
                if not some:
                    return

        # upwards: falling suffixes, and S* as they come by
        falling, last, fresh = ByteQueues(limit, os.path.join(folder, "kept")), [-1], set()
        up = lambda before, own: before >= own
        queue.push(int(text[n - 1]), np.array([(n - 1, 0)], _TUPLE))
        for c in range(256):
            last[0] = -1
            drain(c, up, falling, fresh)
            a, b = int(bounds[c]), int(bounds[c + 1])
            for k in range(a, b, block):
                at, lcp = seeds[k : min(b, k + block)], seed_lcp[k : min(b, k + block)].copy()
                if k == a:
                    lcp[0] = common(last[0], int(at[0])) if last[0] >= 0 else 0
                pass_on(at, lcp, lambda before, own: before > own)
        # downwards: rising suffixes, while falling ones come by from the last to the first
        queue = ByteQueues(limit, os.path.join(folder, "rising"))
        since[:] = depth
        since_all[:] = depth
        result = os.path.join(folder, "array")
        sizes = np.bincount(text, minlength=256)
        ends = np.cumsum(sizes)
        out = np.memmap(result, _TUPLE, "w+", shape=(n,)) if n > limit else np.empty(n, _TUPLE)
        for c in range(255, -1, -1):
            end, prior, carry, first = int(ends[c]), None, 0, True
            while True:  # rising suffixes of c: tuples hold the common prefix with the next larger one
                some = False
                for tuples in queue.pop(c, block):
                    some = True
                    lcp = tuples["lcp"].copy()
                    if first:
                        lcp[0], first = 0, False
                    pass_on(tuples["at"], lcp, lambda before, own: before <= own)
                    m = len(tuples)
                    out["at"][end - m : end] = tuples["at"][::-1]
                    # common prefix with the next smaller one: that of the tuple after it
                    if prior is not None:
                        out["lcp"][prior] = lcp[0]
                    out["lcp"][end - m + 1 : end] = lcp[1:][::-1]
                    end, prior = end - m, end - m
                if not some:
                    break
            blocks = list(falling.pop(c, block))
            if blocks:
                tail = blocks[-1]
                total = sum(map(len, blocks))
                if prior is not None:
                    carry = common(int(tail["at"][-1]), int(out["at"][prior]))
                    out["lcp"][prior] = carry
                at = end
                for tuples in reversed(blocks):
                    m = len(tuples)
                    out[at - m : at] = tuples
                    # going down, each tuple meets the one above it first
                    above = np.empty(m, np.int32)
                    above[:-1] = tuples["lcp"][1:]
                    above[-1] = carry
                    pass_on(tuples["at"][::-1], above[::-1].copy(), lambda before, own: before < own)
                    carry, at = int(tuples["lcp"][0]), at - m
                out["lcp"][end - total] = 0
            elif prior is not None:
                out["lcp"][prior] = 0
        for k in range(0, n, block):
            yield np.array(out["at"][k : k + block]), np.array(out["lcp"][k : k + block])
        del out


def suffix_array(text: bytes, depth: int | None = None, limit: int = 1 << 22, block: int = 1 << 18) -> tuple[np.ndarray, np.ndarray]:
    """Positions and common prefixes of all suffixes of a text without byte 0, by the same method."""
    data = np.append(np.frombuffer(text, np.uint8), 0).astype(np.uint8)
    blocks = list(induce(data, len(data) if depth is None else depth, limit, block))
    return np.concatenate([b[0] for b in blocks])[1:], np.concatenate([b[1] for b in blocks])[1:]
