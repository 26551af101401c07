"""Bloom filters: membership, exact replay of a stream's plain filter, and filters that reset bits."""

from __future__ import annotations

import hashlib
import math
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..checkpoints import cut
from ..functions.keys import positions
from ..functions.murmur import murmur3_128, murmur3_strings

#: Largest bit vector that is broadcast.
MOST_BITS = 1 << 29
#: Elements that a resetting filter looks up at once.
STRETCH = 2000
#: Elements, as a multiple of a filter's places, that are read before a piece of a stream so that the filter's bits no longer
#: depend on how it began (at ten filters of 10,000 places nine to twelve were enough); a piece is as long at least.
FORGETS = 25
#: Pieces from which a stream is read in pieces, elements that a task holds (32 bytes each), and values of seq looked at, for so many
#: elements as are read before a range, to find where to cut.
LANES, HELD, CUTS = 4, 8_000_000, 200


def filters_for(fpr: float) -> int:
    """Number of filters from a false-positive threshold, for filters that settle where half-full-like loads balance."""
    return max(1, round(math.log(fpr) / math.log(1 - 1 / math.e)))


def bits_for(n: int, fpr: float) -> int:
    return math.ceil(-n * math.log(fpr) / math.log(2) ** 2)


# -- membership ---------------------------------------------------------------------------------------------


def build(df: DataFrame, column: str, k: int, bits: int, seed: int = 0) -> DataFrame:
    """The filter as a table: filter, word (64 bits each), mask. Partial ORs go before the shuffle."""
    size = bits // k
    at = df.select(F.posexplode(positions(F.col(column).cast("string"), k, size, seed)).alias("filter", "pos"))
    return at.groupBy("filter", F.floor(F.col("pos") / 64).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(pos % 64 as int))")).alias("mask"))


def might_contain(df: DataFrame, column: str, made: DataFrame, k: int, bits: int, seed: int = 0) -> DataFrame:
    """df with ``hit``: no false negatives. A filter of bounded size is broadcast, a larger one joined."""
    size = bits // k
    probe = df.select(column).distinct().select(F.col(column).alias("_v"), F.posexplode(positions(F.col(column).cast("string"), k, size, seed)).alias("filter", "pos")).withColumn("word", F.floor(F.col("pos") / 64))
    side = F.broadcast(made) if bits <= MOST_BITS else made
    set_ = F.coalesce(F.expr("shiftright(mask, cast(pos % 64 as int)) & 1L"), F.lit(0)) == 1
    seen = probe.join(side, ["filter", "word"], "left").groupBy("_v").agg(F.bool_and(set_).alias("hit"))
    return df.join(seen, df[column] == seen["_v"], "left").drop("_v").withColumn("hit", F.coalesce("hit", F.lit(False)))


# -- duplicates in a stream ---------------------------------------------------------------------------------


def flag_classic(instances: DataFrame, k: int, bits: int, seed: int = 0, form: str = "md5") -> DataFrame:
    """is_dup as one plain filter would say, reading in order of seq, without an order: a bit is set first at the least seq
    that maps to it; an element is seen iff all its bits were set before, so the new ones are those that set a bit first.
    Joins are merged: the optimizer takes the bits for as few as the instances, and would send them all to the driver."""
    size = bits // k
    if form == "md5":
        at = positions(F.col("sig"), k, size, seed)
    else:
        at = F.array(*[F.pmod(F.xxhash64(F.lit(seed), F.lit(i), F.col("sig")), F.lit(size)) for i in range(k)])
    rows = instances.where("seq is not null").select("seq", F.posexplode(at).alias("filter", "pos"))
    first = rows.groupBy((F.col("filter") * F.lit(size).cast("long") + F.col("pos")).alias("bit")).agg(F.min("seq").alias("first"))
    new = first.select(F.col("first").alias("_new")).distinct().hint("merge")
    return instances.where("seq is not null").join(new, F.col("seq") == F.col("_new"), "left").withColumn("is_dup", F.col("_new").isNull()).drop("_new")


class ResettingFilter:
    """k bit vectors that share ``bits``; an element is seen iff all its bits are set. What a new one does:

    - ``balanced``: each filter clears a random bit with a probability of its load, then the element's bit is set;
    - ``reservoir``: it goes in with a probability that falls with the stream, clearing a random bit of each filter;
    - ``biased``: always goes in, clearing a random bit of each filter;
    - ``biased_single``: always goes in, clearing a random bit of one filter;
    - ``none``: the plain filter.
    """

    def __init__(self, k: int, bits: int, policy: str = "balanced", state: bytes | None = None):
        self.k, self.size, self.policy = k, max(1, bits // k), policy
        self.bits = [bytearray(self.size) for _ in range(k)]
        self.load, self.seen, self.cleared = [0] * k, 0, 0
        if state:
            whole = np.frombuffer(state, np.uint8)
            self.seen = int(whole[:8].view(np.int64)[0])
            flat = np.unpackbits(whole[8:], count=k * self.size)
            self.bits = [bytearray(flat[i * self.size : (i + 1) * self.size].tobytes()) for i in range(k)]
            self.load = [sum(b) for b in self.bits]

    def state(self) -> bytes:
        return np.int64(self.seen).tobytes() + np.packbits(np.frombuffer(b"".join(self.bits), np.uint8)).tobytes()

    def add(self, at: list[int], where: list[int], chance: list[float]) -> bool:
        """Tests and adds one element: its k positions, k random places, k + 1 random numbers in [0, 1)."""
        self.seen += 1
        for b, a in zip(self.bits, at, strict=True):
            if not b[a]:
                break
        else:
            return True
        load, size, policy = self.load, self.size, self.policy
        if policy == "reservoir" and chance[self.k] >= min(1.0, size / self.seen):
            return False
        one = int(chance[self.k] * self.k) if policy == "biased_single" else -1
        for i, b in enumerate(self.bits):
            if (chance[i] < load[i] / size if policy == "balanced" else policy in ("biased", "reservoir") or i == one) and b[where[i]]:
                b[where[i]] = 0
                load[i] -= 1
                self.cleared += 1
            if not b[at[i]]:
                b[at[i]] = 1
                load[i] += 1
        return False

    def has(self, at: np.ndarray) -> np.ndarray:
        """Which rows of positions have all bits set now."""
        out = np.ones(len(at), bool)
        for i, b in enumerate(self.bits):
            out &= np.frombuffer(b, np.uint8)[at[:, i]] > 0
        return out

    def add_all(self, at: np.ndarray, random: Callable[[np.ndarray], tuple[list, list]]) -> list[bool]:
        """``add`` for rows of positions, in order; ``random``: random places and numbers of rows. Where most are seen, as in a filter with
        room, numbers are drawn only for those that aren't, and what was seen stays so until a bit is cleared."""
        known = self.has(at)
        new = np.flatnonzero(~known)
        if not len(new):
            self.seen += len(at)
            return known.tolist()
        if len(new) * 8 > len(at):
            return [self.add(*x) for x in zip(at.tolist(), *random(np.arange(len(at))), strict=True)]
        drawn = dict(zip(new.tolist(), zip(*random(new), strict=True), strict=True))
        out, start = known.tolist(), self.cleared
        for j in range(len(out)):
            if out[j] and self.cleared == start:
                self.seen += 1
                continue
            own = at[j].tolist()
            if j not in drawn and not all(b[a] for b, a in zip(self.bits, own, strict=True)):
                drawn[j] = tuple(x[0] for x in random(np.array([j])))
            out[j] = self.add(own, *drawn.get(j, ((), ())))
        return out


    def add_hashed(self, both: np.ndarray) -> int:
        """Adds elements in order by their hashes and those for their random numbers; how many were seen."""
        flagged = 0
        for i in range(0, len(both), STRETCH):
            h = both[i : i + STRETCH]
            flagged += sum(self.add_all(places_of(h[:, :2], self.k, self.size), lambda r, h=h: tuple(x.tolist() for x in chances_of(h[r, 2:], self.k, self.size))))
        return flagged


def draws(signatures: list[str], seqs: list[int], k: int, size: int, seed: int, form: str = "murmur128"):
    """Positions by double hashing of a 128-bit digest, and random places and numbers that depend on (seq, signature)."""
    return places(signatures, k, size, seed, form).tolist(), *chances(signatures, seqs, k, size, seed)


def places(signatures: list[str], k: int, size: int, seed: int, form: str = "murmur128") -> np.ndarray:
    return places_of(_digits(pa.array(signatures, pa.string())) if form == "md5" else murmur3_128([s.encode() for s in signatures], seed), k, size)


def chances(signatures: list[str], seqs: list[int], k: int, size: int, seed: int) -> tuple[list, list]:
    noise = murmur3_128([b"%d|%d|" % (seed, s) + g.encode() for s, g in zip(seqs, signatures, strict=True)], seed + 1)
    return tuple(x.tolist() for x in chances_of(noise, k, size))


def flag_balanced(instances: DataFrame, bits: int, fpr: float | None = None, k: int | None = None, seed: int = 0, shards: int = 1, policy: str = "balanced", form: str = "murmur128") -> DataFrame:
    """instances (sig, seq) with is_dup from filters that reset. Shards are dealt by signature, so all copies of an
    instance meet; each has bits/shards of memory and reads in order of (seq, sig). shards=1 is the paper's single stream."""
    k = k or filters_for(fpr)
    own = bits // shards

    def run(batches):
        made: dict[int, ResettingFilter] = {}
        for b in batches:
            sig, seq, shard = b.column("sig").to_pylist(), b.column("seq").to_pylist(), b.column("shard").to_numpy()
            out, size = np.zeros(len(sig), bool), max(1, own // k)
            for s in np.unique(shard).tolist():
                if s not in made:
                    made[s] = ResettingFilter(k, own, policy)
                mine = np.flatnonzero(shard == s)
                for i in range(0, len(mine), STRETCH):
                    rows = mine[i : i + STRETCH].tolist()
                    gs, qs = [sig[x] for x in rows], [seq[x] for x in rows]
                    out[rows] = made[s].add_all(places(gs, k, size, seed, form), lambda r, gs=gs, qs=qs: chances([gs[x] for x in r], [qs[x] for x in r], k, size, seed))
            yield pa.RecordBatch.from_arrays([b.column("seq"), b.column("sig"), pa.array(out, pa.bool_())], names=["seq", "sig", "is_dup"])

    dealt = instances.select(F.col("seq").cast("long").alias("seq"), F.col("sig").cast("string").alias("sig"), F.pmod(F.xxhash64("sig"), F.lit(shards)).cast("int").alias("shard"))
    return dealt.repartition(shards, "shard").sortWithinPartitions("seq", "sig").mapInArrow(run, "seq long, sig string, is_dup boolean")


def count_balanced(instances: DataFrame, bits: int, fpr: float | None = None, k: int | None = None, seed: int = 0, policy: str = "balanced", form: str = "murmur128", forgets: int = FORGETS) -> tuple[int, int] | None:
    """``count_settings`` of one setting."""
    return count_settings(instances, [(k or filters_for(fpr), bits)], seed, policy, form, forgets)[0]


def count_settings(instances: DataFrame, settings: list[tuple[int, int]], seed: int = 0, policy: str = "balanced", form: str = "murmur128", forgets: int = FORGETS, held: int = HELD) -> list[tuple[int, int] | None]:
    """For each (filters, bits): instances that the single stream of ``flag_balanced`` leaves unflagged, and all: the same numbers. Tasks
    take ranges of seq and hash their elements, once for all settings. A filter that resets forgets, so a task begins with the last elements
    before its range, in an empty filter, and reads pieces of its range abreast, each begun likewise (``Lanes``). The bits at the start
    of a piece are compared with those at the end of the piece before; where they differ, it is read again from the right bits. A
    long stream through a filter that does not forget in it is hashed in tasks and read by one. None for short streams."""
    n, sizes = instances.count(), [max(1, bits // k) for k, bits in settings]
    spread = [j for j, size in enumerate(sizes) if policy in ("balanced", "biased", "biased_single") and n // (forgets * size) >= LANES]
    single = [j for j in range(len(sizes)) if j not in spread and n > held // 2]
    if not spread and not single:
        return [None] * len(settings)
    warm = max((forgets * sizes[j] for j in spread), default=0)
    tasks = max(-(-n // held), min(instances.sparkSession.sparkContext.defaultParallelism, n // (LANES * warm) if spread else n))
    rows = instances.select(F.col("seq").cast("long").alias("seq"), F.col("sig").cast("string").alias("sig"))
    # where ranges are cut, and where reading begins before a cut, changes no number
    reach = max(warm, n // (20 * tasks)) if spread else 0
    some = np.sort(rows.where("seq is not null").select("seq").where(F.rand(0) < min(1.0, CUTS / max(reach, n // (20 * tasks), 1))).toArrow()["seq"].to_numpy())
    if not len(some):
        return [None] * len(settings)
    at = np.arange(1, tasks) * len(some) // tasks
    cuts, begins = some[at], some[np.maximum(0, at - -(-len(some) * reach // n))]

    def deal(batches):
        for b in batches:
            seq = b.column("seq").fill_null(-(2**63)).to_numpy()
            own = np.searchsorted(cuts, seq, "right")
            # a row is also read before the ranges that begin after it and whose reading begins at or before it
            also = np.maximum(np.searchsorted(begins, seq, "right"), own)
            times = also - own + 1
            which = np.repeat(np.arange(len(seq)), times)
            of = own[which] + np.arange(len(which)) - np.repeat(np.cumsum(times) - times, times)
            yield pa.RecordBatch.from_arrays([pa.array(of, pa.int32()), *(b.column(c).take(pa.array(which)) for c in ("seq", "sig"))], names=["of", "seq", "sig"])

    dealt = rows.mapInArrow(deal, "of int, seq long, sig string")

    def hashed(batches):
        """Task, its elements' seq (null least) and hashes, in order, batch by batch and task by task."""
        for b in batches:
            of, seq, sig = b.column("of").to_numpy(), b.column("seq"), b.column("sig")
            ends = [*(np.flatnonzero(of[1:] != of[:-1]) + 1).tolist(), len(of)] if len(of) else []
            both = np.concatenate([_digits(sig) if form == "md5" else murmur3_strings(sig, seed), murmur3_strings(_noise_text(sig, seq, seed), seed + 1)], 1)
            for lo, hi in zip([0, *ends], ends, strict=False):
                yield int(of[lo]), seq.slice(lo, hi - lo).fill_null(-(2**63)).to_numpy(), both[lo:hi]

    def run(batches, these=spread, single=single, begin=None):
        parts: dict[int, list] = {}
        for i, (r, seq, both) in enumerate(hashed(batches)):
            own = parts.setdefault(r, [0, bytearray()])
            early = int((seq < cuts[r - 1]).sum()) if r else 0
            if these:
                own[0] += early
                own[1] += both.tobytes()
            if single:
                yield pa.RecordBatch.from_pylist([{"of": r, "i": i, "body": both[early:].tobytes()}], pa.schema(_RANGE_ARROW))
        for r, (before, body) in parts.items():
            both = np.frombuffer(body, np.uint64).reshape(-1, 4)
            for j in these:
                yield pa.RecordBatch.from_pylist([{"of": r, "i": j, **_abreast(both, before, *settings[j], policy, forgets * sizes[j], begin)}], pa.schema(_RANGE_ARROW))

    def read(batches):
        filters, whole, flagged = {j: ResettingFilter(*settings[j], policy) for j in single}, 0, dict.fromkeys(single, 0)
        for b in batches:
            for body in b.column("body"):
                both = np.frombuffer(body.as_buffer(), np.uint64).reshape(-1, 4)
                whole += len(both)
                for j, f in filters.items():
                    flagged[j] += f.add_hashed(both)
        yield pa.RecordBatch.from_pylist([{"i": j, "n": whole, "flagged": x} for j, x in flagged.items()], pa.schema(_RANGE_ARROW))

    done = dealt.repartitionById(tasks, "of").sortWithinPartitions("of", "seq", "sig").mapInArrow(run, _RANGE)
    out: list[tuple[int, int] | None] = [None] * len(settings)
    if single:
        done = cut(done)
        for x in done.where("body is not null").repartition(1).sortWithinPartitions("of", "i").mapInArrow(read, _RANGE).collect():
            out[x.i] = (x.n - x.flagged, x.n)
    found = {(x.i, x.of): x for x in done.where("body is null").collect()} if spread else {}  # a row for each task and setting
    for j in spread:
        state, whole, flagged = None, 0, 0
        for r in sorted(r for i, r in found if i == j and found[i, r].n):
            x = found[j, r]
            if state is not None and _digest(state) != x.start:
                again = dealt.where(F.col("of") == r).repartition(1).sortWithinPartitions("seq", "sig")
                x = again.mapInArrow(lambda batches, j=j, begin=bytes(state): run(batches, [j], [], begin), _RANGE).first()
            state, whole, flagged = x.state, whole + x.n, flagged + x.flagged
        out[j] = (whole - flagged, whole)
    return out


_RANGE = "of int, i int, n long, flagged long, start binary, state binary, body binary"
_RANGE_ARROW = [("of", pa.int32()), ("i", pa.int32()), ("n", pa.int64()), ("flagged", pa.int64()), ("start", pa.binary()), ("state", pa.binary()), ("body", pa.binary())]


def _abreast(both: np.ndarray, before: int, k: int, bits: int, policy: str, warm: int, begin: bytes | None) -> dict:
    """Reads hashed elements, the first ``before`` only to fill the filter (not at all where the bits at the start are known)."""
    n = len(both) - before
    pieces = max(1, n // warm)
    starts = [before + n * j // pieces for j in range(pieces + 1)]
    first = before if begin is not None else max(0, before - warm)
    lanes = Lanes(k, bits, policy, both, [(first, starts[0], starts[1])] + [(max(0, s - warm), s, e) for s, e in zip(starts[1:], starts[2:], strict=False)], begin)
    start, state, flagged = lanes.begun[0], None, 0
    for j in range(pieces):
        if state is None or _digest(state) == _digest(lanes.begun[j]):
            state, flagged = lanes.state(j), flagged + int(lanes.flagged[j])
        else:
            f = ResettingFilter(k, bits, policy, state)
            flagged += f.add_hashed(both[starts[j] : starts[j + 1]])
            state = f.state()
    return {"n": n, "flagged": flagged, "start": _digest(start), "state": state}


class Lanes:
    """Filters of one kind that read pieces of a stream abreast, an element of each at a step: what ``ResettingFilter`` does, for all
    at once. Pieces are (first element read, first that counts, end)."""

    def __init__(self, k: int, bits: int, policy: str, both: np.ndarray, pieces: list[tuple[int, int, int]], begin: bytes | None = None):
        self.k, self.size, self.policy, self.both = k, max(1, bits // k), policy, both
        self.bits = np.zeros(len(pieces) * k * self.size, bool)
        self.load, self.flagged = np.zeros((len(pieces), k)), np.zeros(len(pieces), np.int64)
        self.begun: list[bytes] = [b""] * len(pieces)
        if begin is not None:
            f = ResettingFilter(k, bits, policy, begin)
            self.bits[: k * self.size], self.load[0] = np.frombuffer(b"".join(f.bits), bool), f.load
        # counts begin at the same step in all pieces, so that only begins and ends of reading differ
        low, at = np.array([p[0] - p[1] for p in pieces]), np.array([p[1] for p in pieces])
        high = np.array([p[2] - p[1] for p in pieces])
        edges = sorted({0, *low.tolist(), *high.tolist()})
        for lo, hi in zip(edges, edges[1:], strict=False):
            if lo == 0:
                self.begun = [self.state(j) for j in range(len(pieces))]
            live = np.flatnonzero((low <= lo) & (high >= hi))
            step = max(64, STRETCH * 25 // len(live)) if len(live) else hi - lo
            for t in range(lo, hi, step):
                seen = self._steps(live, at[live] + t, min(step, hi - t))
                if lo >= 0:
                    self.flagged[live] += seen
        if edges[-1] == 0:
            self.begun = [self.state(j) for j in range(len(pieces))]

    def state(self, j: int) -> bytes:
        width = self.k * self.size
        return bytes(8) + np.packbits(self.bits[j * width : (j + 1) * width]).tobytes()

    def _steps(self, live: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
        """Reads n elements from these places; how many each lane had seen."""
        k, size, bits = self.k, self.size, self.bits
        both = self.both[at + np.arange(n)[:, None]].reshape(-1, 4)
        base = ((live * k)[:, None] + np.arange(k)) * size
        own = places_of(both[:, :2], k, size).reshape(n, len(live), k) + base
        where, chance = chances_of(both[:, 2:], k, size)
        where = where.reshape(n, len(live), k) + base
        chance = chance.reshape(n, len(live), k + 1)
        one = (chance[:, :, k] * k).astype(np.int64)[:, :, None] == np.arange(k) if self.policy == "biased_single" else None
        chance = np.ascontiguousarray(chance[:, :, :k])
        load, out = self.load[live], np.zeros(len(live), np.int64)
        for j in range(n):
            a, w = own[j], where[j]
            seen = bits.take(a).all(1)
            out += seen
            new = ~seen[:, None]
            set_ = bits.take(w)
            clear = set_ & new
            if self.policy == "balanced":
                clear &= chance[j] < load / size
            elif one is not None:
                clear &= one[j]
            bits.put(w, set_ ^ clear)
            known = bits.take(a)
            add = new > known
            bits.put(a, known | add)
            load += add
            load -= clear
        self.load[live] = load
        return out


def places_of(h: np.ndarray, k: int, size: int) -> np.ndarray:
    """Positions by double hashing."""
    return ((h[:, :1] + np.arange(k, dtype=np.uint64) * (h[:, 1:] | np.uint64(1))) % np.uint64(size)).astype(np.int64)


def chances_of(noise: np.ndarray, k: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """k random places and k + 1 random numbers in [0, 1)."""
    wide = noise[:, :1] + np.arange(2 * k + 1, dtype=np.uint64) * (noise[:, 1:] | np.uint64(1))
    wide = (wide ^ (wide >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return ((wide[:, :k] >> np.uint64(11)) % np.uint64(size)).astype(np.int64), (wide[:, k:] >> np.uint64(11)) / float(1 << 53)


def _digits(sig: pa.Array) -> np.ndarray:
    return np.array([[int(s[:16], 16), int(s[16:32], 16) | 1] for s in sig.to_pylist()], np.uint64).reshape(-1, 2)


def _noise_text(sig: pa.Array, seq: pa.Array, seed: int) -> pa.Array:
    return pc.binary_join_element_wise(pa.scalar(str(seed)), seq.cast(pa.string()), sig.cast(pa.string()), "|")


def _digest(state: bytes) -> bytes:
    """Of the bits alone: only ``reservoir`` looks at the number of elements."""
    return hashlib.md5(state[8:]).digest()


def candidates(instances: DataFrame, k: int, bits: int, seed: int = 0) -> DataFrame:
    """Instances whose bits were all hit twice or more: a superset of the repeated ones, found without a shuffle of
    instances; only these need the exact grouping. Hits are counted (up to two) by bit."""
    size = bits // k
    at = lambda df: df.select("seq", "sig", F.posexplode(positions(F.col("sig"), k, size, seed)).alias("filter", "pos"))
    twice = at(instances).groupBy("filter", "pos").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("filter", "pos")
    hit = at(instances).join(twice, ["filter", "pos"], "left_semi").groupBy("seq", "sig").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == k)
    return hit.select("seq", "sig")


class QuotientFilter:
    """Approximate membership in one table of slots: a hash is a quotient (its home slot) and a remainder (what the slot
    holds). Remainders of one quotient stand sorted in a run, runs in order of their quotients in clusters; three bits a
    slot tell whether its quotient has a run, whether the slot continues one, and whether it stands away from home.
    It can be merged and resized, unlike a bit vector: the remainder lends its top bit to the quotient. Doubles by
    itself when nine tenths full, while there are bits to lend."""

    def __init__(self, quotient_bits: int, remainder_bits: int):
        self.q, self.r, self.count = quotient_bits, remainder_bits, 0
        n = 1 << quotient_bits
        self.slots, self.has_run, self.continues, self.moved = array("Q", bytes(8 * n)), bytearray(n), bytearray(n), bytearray(n)

    def _split(self, h: int) -> tuple[int, int]:
        h &= (1 << (self.q + self.r)) - 1
        return h >> self.r, h & ((1 << self.r) - 1)

    def _free(self, at: int) -> bool:
        return not (self.has_run[at] or self.continues[at] or self.moved[at])

    def _run(self, quotient: int) -> int:
        """Where the run of a quotient begins (or would): back to the start of the cluster, then run by run."""
        last = len(self.slots) - 1
        home = quotient
        while self.moved[home]:
            home = (home - 1) & last
        at = home
        while home != quotient:
            at = (at + 1) & last
            while self.continues[at]:
                at = (at + 1) & last
            home = (home + 1) & last
            while not self.has_run[home]:
                home = (home + 1) & last
        return at

    def _find(self, quotient: int, remainder: int) -> tuple[int, int, bool]:
        """Start of the run, place for the remainder in it, and whether it is there."""
        last = len(self.slots) - 1
        start = at = self._run(quotient)
        while True:
            if self.slots[at] >= remainder:
                return start, at, self.slots[at] == remainder
            at = (at + 1) & last
            if not self.continues[at]:
                return start, at, False

    def add(self, h: int) -> bool:
        """Adds a hash; whether it was there."""
        quotient, remainder = self._split(h)
        last = len(self.slots) - 1
        if self._free(quotient):
            self.slots[quotient], self.has_run[quotient] = remainder, 1
        else:
            known, continues = self.has_run[quotient], 0
            self.has_run[quotient] = 1
            if known:
                start, at, there = self._find(quotient, remainder)
                if there:
                    return True
                continues = int(at != start)
                if not continues:
                    self.continues[start] = 1  # the old first one, which moves on
            else:
                at = self._run(quotient)
            held, moved = remainder, int(at != quotient)
            while True:  # each later one moves a slot on
                free = self._free(at)
                self.slots[at], held = held, self.slots[at]
                self.continues[at], continues = continues, self.continues[at]
                self.moved[at] = moved
                if free:
                    break
                at, moved = (at + 1) & last, 1
        self.count += 1
        if self.count * 10 > 9 * len(self.slots) and self.r > 1:
            self.__dict__.update(self.grow().__dict__)
        return False

    def __contains__(self, h: int) -> bool:
        quotient, remainder = self._split(h)
        return bool(self.has_run[quotient]) and self._find(quotient, remainder)[2]

    def hashes(self) -> Iterator[int]:
        """What it holds, quotient by quotient."""
        last = len(self.slots) - 1
        for quotient in range(len(self.slots)):
            if self.has_run[quotient]:
                at = self._run(quotient)
                yield quotient << self.r | self.slots[at]
                while self.continues[at := (at + 1) & last]:
                    yield quotient << self.r | self.slots[at]

    def merge(self, other: QuotientFilter) -> QuotientFilter:
        for h in other.hashes():
            self.add(h)
        return self

    def grow(self) -> QuotientFilter:
        """Twice the quotients, one bit less of remainder; holds the same hashes."""
        out = QuotientFilter(self.q + 1, self.r - 1)
        for h in self.hashes():
            out.add(h)
        return out


def flag_quotient(instances: DataFrame, quotient_bits: int = 20, remainder_bits: int = 16, seed: int = 0, shards: int = 1) -> DataFrame:
    """is_dup by a quotient filter of each shard, in order of seq."""

    def run(batches):
        made: dict[int, QuotientFilter] = {}
        for b in batches:
            h = murmur3_128([s.encode() for s in b.column("sig").to_pylist()], seed)[:, 0].tolist() if b.num_rows else []
            out = []
            for s, x in zip(b.column("shard").to_pylist(), h, strict=True):
                if s not in made:
                    made[s] = QuotientFilter(quotient_bits, remainder_bits)
                out.append(made[s].add(x))
            yield pa.RecordBatch.from_arrays([b.column("seq"), b.column("sig"), pa.array(out, pa.bool_())], names=["seq", "sig", "is_dup"])

    dealt = instances.select(F.col("seq").cast("long").alias("seq"), "sig", F.pmod(F.xxhash64("sig"), F.lit(shards)).cast("int").alias("shard"))
    return dealt.repartition(shards, "shard").sortWithinPartitions("seq").mapInArrow(run, "seq long, sig string, is_dup boolean")
