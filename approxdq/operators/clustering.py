"""Clustering coefficient: exact, by a random walk, and by independent draws of the walk's steady state."""

from __future__ import annotations

import bisect
import hashlib
import math
import tempfile
import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..checkpoints import checkpoint_folder, cut
from ..deploy import ship
from ..functions.keys import number, random_key
from . import coloured

#: Largest number of directed edges whose neighbour lists are sent to the walkers; beyond it walkers move by look-ups.
MOST_EDGES = 20_000_000


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("d"))


# -- exact --------------------------------------------------------------------------------------------------


def triangles(edges: DataFrame) -> DataFrame:
    """a, b, c of each triangle once. Edges point to the end of higher degree, so a hub heads few wedges."""
    d = degrees(edges)
    ranked = edges.join(d.select(F.col("v").alias("src"), F.col("d").alias("ds")), "src").join(d.select(F.col("v").alias("dst"), F.col("d").alias("dd")), "dst")
    up = ranked.where((F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))).select("src", "dst", "dd")
    wedge = up.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("dd").alias("db")).join(up.select(F.col("src").alias("a"), F.col("dst").alias("c"), F.col("dd").alias("dc")), "a")
    wedge = wedge.where((F.col("db") < F.col("dc")) | ((F.col("db") == F.col("dc")) & (F.col("b") < F.col("c"))))
    return wedge.join(edges.select(F.col("src").alias("b"), F.col("dst").alias("c")), ["b", "c"], "left_semi").select("a", "b", "c")


def local(edges: DataFrame) -> DataFrame:
    """v, d, t (triangles at v), c: links among neighbours over possible ones; 0 below degree 2."""
    at = triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("t"))
    c = F.when(F.col("d") < 2, 0.0).otherwise(2 * F.col("t") / (F.col("d") * (F.col("d") - 1)))
    return degrees(edges).join(at, "v", "left").select("v", "d", F.coalesce("t", F.lit(0)).alias("t")).withColumn("c", c)


def count_triangles(edges: DataFrame) -> DataFrame:
    """Number of triangles. Numbered edges are dealt by colours, as in ``exact`` and ``exact_global``."""
    if not numbered(edges):
        return triangles(edges).agg(F.count(F.lit(1)).alias("n"))
    units = coloured.Units(edges)
    n = units.triangles().agg(F.coalesce(F.sum("found"), F.lit(0)).alias("n"))
    units.drop()
    return n


def numbered(edges: DataFrame) -> bool:
    """Whether vertices are numbers: such edges may repeat and stand in one direction, and all work on them is done by ``coloured``."""
    return dict(edges.dtypes)["src"] == "bigint"


def exact(edges: DataFrame) -> DataFrame:
    """Average over vertices of the local coefficient."""
    if numbered(edges):
        units = coloured.Units(edges)
        per = units.vertices(units.triangles(each=True))
        units.drop()
        return per.agg((F.sum("c") / F.sum("vertices")).alias("value"), F.coalesce(F.sum("vertices"), F.lit(0)).alias("vertices"))
    return local(edges).agg(F.avg("c").alias("value"), F.count(F.lit(1)).alias("vertices"))


def exact_pairs(edges: DataFrame) -> DataFrame:
    """The literal baseline: every pair of neighbours is tested. Sum of squared degrees; for small graphs."""
    x, y = edges.select(F.col("src").alias("v"), F.col("dst").alias("a")), edges.select(F.col("src").alias("v"), F.col("dst").alias("b"))
    closing = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(1).alias("closed"))
    pairs = x.join(y, "v").where("a < b").join(closing, ["a", "b"], "left").groupBy("v").agg(F.coalesce(F.sum("closed"), F.lit(0)).alias("t"), F.count(F.lit(1)).alias("pairs"))
    return degrees(edges).join(pairs, "v", "left").agg(F.avg(F.coalesce(F.col("t") / F.col("pairs"), F.lit(0.0))).alias("value"), F.count(F.lit(1)).alias("vertices"))


def exact_global(edges: DataFrame) -> DataFrame:
    """Closed wedges over wedges."""
    if numbered(edges):
        units = coloured.Units(edges)
        closed, wedges = units.triangles().agg((3 * F.sum("found")).alias("closed")), units.vertices().agg(F.sum("wedges").alias("wedges"))
        units.drop()
        sums = closed.crossJoin(wedges)
    else:
        sums = local(edges).agg(F.sum("t").alias("closed"), F.sum(F.expr("d * (d - 1) div 2")).alias("wedges"))
    return sums.select("closed", "wedges", (F.col("closed") / F.col("wedges")).alias("value"))


# -- walk ---------------------------------------------------------------------------------------------------


def steps_for(vertices: int, m: float, base: float = math.e) -> int:
    """r = m log^2 n, three at least (half up)."""
    return max(3, math.floor(m * (math.log(vertices) / math.log(base)) ** 2 + 0.5)) if vertices > 1 else 3


def neighbours(edges: DataFrame) -> DataFrame:
    """v, i (from 0, by name), nbr, d."""
    w = Window.partitionBy("src")
    return edges.select(F.col("src").alias("v"), (F.row_number().over(w.orderBy("dst")) - 1).alias("i"), F.col("dst").alias("nbr"), F.count(F.lit(1)).over(w).alias("d"))


def _start(edges: DataFrame, walkers: int, seed: int, start: str) -> DataFrame:
    """walker, v: vertices by least key (``uniform``), or sources of edges by least key (``degree``)."""
    rows = edges.select(F.col("src").alias("v")).distinct().withColumn("key", random_key(seed, F.lit("start"), "v")) if start == "uniform" else edges.select(F.col("src").alias("v"), random_key(seed, F.lit("start"), "src", "dst").alias("key"))
    first = rows.orderBy("key", "v").limit(walkers)
    return first.select((F.row_number().over(Window.orderBy("key", "v")) - 1).alias("walker"), "v")  # ``walkers`` rows


def walk(edges: DataFrame, m: float = 1.0, seed: int = 0, walkers: int = 1, start: str = "uniform", steps: int | None = None, most_edges: int = MOST_EDGES, kinds: str = "") -> DataFrame:
    """walker, step (from 1), v, d, before, after and closed. Edges are read several times, so give written
    ones. Each next vertex is the neighbour whose number is a digest of (seed, walker, step) modulo
    the degree. Walkers share the r steps. Edges go both ways, so a dead end turns back. Numbered edges need not be
    written, may repeat and stand in one direction; ``kinds`` are the letters of their vertices."""
    if numbered(edges):
        return _walk_packed(edges, kinds, m, seed, walkers, start, steps)
    if edges.count() > most_edges:
        lists = Files(edges)
        r = steps or steps_for(lists.vertices, m)
        first = [(x.walker, x.v) for x in _start(edges, walkers, seed, start).collect()]  # ``walkers`` rows
        return _walk_files(edges, lists, first, max(3, -(-r // walkers)), seed)
    lists = Lists(edges)
    r = steps or steps_for(len(lists.names), m)
    if start == "uniform":
        first = sorted((hashlib.md5(f"{seed}|start|{v}".encode()).hexdigest(), v) for v in lists.names.to_pylist())[:walkers]
        rows = [(w, v) for w, (_, v) in enumerate(first)]
    else:
        rows = [(x.walker, x.v) for x in _start(edges, walkers, seed, start).collect()]  # ``walkers`` rows
    return _walk_lists(edges.sparkSession, lists, rows, max(3, -(-r // walkers)), seed)


class Lists:
    """Neighbour lists of a graph of checked size: vertices by name, and the numbers of each one's neighbours, rising."""

    def __init__(self, edges: DataFrame):
        rows = edges.orderBy("src", "dst").select("src", "dst").toArrow()
        src, dst = (rows[c].combine_chunks().cast(pa.string()) for c in ("src", "dst"))
        ends = np.append(pc.not_equal(src[1:], src[:-1]).to_numpy(zero_copy_only=False), True) if len(src) else np.zeros(0, bool)
        self.names = src.filter(pa.array(ends))
        self.offsets = np.append(0, np.flatnonzero(ends) + 1)
        self.nbr = pc.index_in(dst, self.names).to_numpy().astype(np.int32)

    def of(self, v: int) -> np.ndarray:
        return self.nbr[self.offsets[v] : self.offsets[v + 1]]

    def linked(self, u: int, v: int) -> bool:
        own = self.of(u)
        at = int(np.searchsorted(own, v))
        return at < len(own) and int(own[at]) == v

    def path(self, v: int, steps: int, walker: object, seed: int, less: int | None = None) -> list[int]:
        """Vertices of a walk from v; ``less``: without the link between v and this one."""
        out, first = [], v
        for t in range(1, steps + 1):
            out.append(v)
            own = self.of(v)
            if less is not None and v in (first, less):
                own = own[own != (less if v == first else first)]
            if not len(own):
                break
            v = int(own[int(hashlib.md5(f"{seed}|{walker}|{t}".encode()).hexdigest()[:8], 16) % len(own)])
        return out


_STEPS = "walker int, step int, v string, d long, before string, after string, closed int"


def _walk_lists(spark: SparkSession, lists: Lists, first: list[tuple[int, str]], each: int, seed: int) -> DataFrame:
    """Neighbour lists of a checked size go to the walkers, who also note degrees and whether each wedge is closed."""
    shared = ship(spark).sparkContext.broadcast(lists)

    def run(batches):
        own = shared.value
        for b in batches:
            for w, v in zip(b.column("walker").to_pylist(), b.column("v").to_pylist(), strict=True):
                at = own.path(pc.index(own.names, v).as_py(), each, w, seed)
                name = [own.names[i].as_py() for i in at]
                closed = [None] + [int(own.linked(x, y)) for x, y in zip(at, at[2:], strict=False)] + [None]
                columns = [pa.array([w] * len(at), pa.int32()), pa.array(range(1, len(at) + 1), pa.int32()), pa.array(name, pa.string()), pa.array([len(own.of(i)) for i in at], pa.int64()), pa.array([None] + name[:-1], pa.string()), pa.array(name[1:] + [None], pa.string()), pa.array(closed[: len(at)], pa.int32())]
                yield pa.RecordBatch.from_arrays(columns, names=[f.split()[0] for f in _STEPS.split(", ")])

    return spark.createDataFrame(first, "walker int, v string").mapInArrow(run, _STEPS)


class Files:
    """Numbered neighbours of a graph of any size, in Parquet files by ranges of vertices. The driver knows the range of each file
    and reads, at a step, only the files of the vertices where walkers stand: some rows of each, by the statistics in the file."""

    #: Neighbours of a vertex that a look-up brings at once; beyond them the drawn one is looked up by its number.
    FEW = 256

    def __init__(self, edges: DataFrame):
        self.spark = edges.sparkSession
        self.folder = f"{checkpoint_folder(self.spark)}/neighbours-{uuid.uuid4().hex}"
        numbered = neighbours(edges.repartitionByRange("src"))
        numbered.write.parquet(self.folder)
        self.rows = self.spark.read.schema(numbered.schema).parquet(self.folder)
        ends = self.rows.groupBy(F.input_file_name().alias("file")).agg(F.min("v").alias("least"), F.max("v").alias("most"), F.count_if(F.col("i") == 0).alias("n")).collect()  # a row for each file
        self.ends, self.vertices = [(e.file, e.least, e.most) for e in ends], sum(e.n for e in ends)

    def _rows(self, of: list[str], also: Column) -> list:
        """Rows of these vertices (one for each walker at most) that hold ``also``."""
        files = [f for f, least, most in self.ends if any(least <= v <= most for v in of)]
        if not files:
            return []
        named = [F.col("v") == v for v in of]
        return self.spark.read.schema(self.rows.schema).parquet(*files).where(_any(named) & also).collect()

    def next(self, at: dict[int, str], draw: dict[int, int]) -> dict[int, tuple[int, str]]:
        """Degree, and the neighbour that the draw names, of each walker's vertex."""
        near: dict[tuple[str, int], str] = {}
        d: dict[str, int] = {}
        for r in self._rows(sorted(set(at.values())), F.col("i") < self.FEW):
            near[r.v, r.i], d[r.v] = r.nbr, r.d
        want = {w: (v, draw[w] % d[v]) for w, v in at.items()}
        far = sorted({x for x in want.values() if x not in near})
        if far:
            for r in self._rows(sorted({v for v, _ in far}), _any([(F.col("v") == v) & (F.col("i") == i) for v, i in far])):
                near[r.v, r.i] = r.nbr
        return {w: (d[x[0]], near[x]) for w, x in want.items()}

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def _any(tests: list[Column]) -> Column:
    """Any of the tests, as a tree of low depth."""
    while len(tests) > 1:
        tests = [x | y for x, y in zip(tests[::2], tests[1::2], strict=False)] + tests[len(tests) - len(tests) % 2 :]
    return tests[0]


def _walk_files(edges: DataFrame, lists: Files, first: list[tuple[int, str]], each: int, seed: int) -> DataFrame:
    """The driver moves the walkers, few as they are, by look-ups; neither a round nor a join reads the graph. Whether wedges are
    closed is one scan of the edges, to which the pairs of all steps are sent."""
    at, rows = dict(first), []
    for t in range(1, each + 1):
        got = lists.next(at, {w: int(hashlib.md5(f"{seed}|{w}|{t}".encode()).hexdigest()[:8], 16) for w in at})
        rows += [(w, t, at[w], got[w][0]) for w in at]
        at = {w: got[w][1] for w in at}
    lists.drop()
    name = {(w, t): v for w, t, v, _ in rows}
    whole = [(w, t, v, d, name.get((w, t - 1)), name.get((w, t + 1))) for w, t, v, d in rows]
    spark = edges.sparkSession
    pairs = spark.createDataFrame(sorted({(b, a) for *_, b, a in whole if b is not None and a is not None}), "src string, dst string")
    linked = {(r.src, r.dst) for r in edges.join(F.broadcast(pairs), ["src", "dst"], "left_semi").collect()}  # a pair for each step at most
    return spark.createDataFrame([(*x, None if None in x[4:] else int(x[4:] in linked)) for x in whole], _STEPS)


#: Largest number of directed edges (with repeats) that one task's local file holds, four or eight bytes each, and directed edges of
#: a task that packs them, about.
MOST_PACKED, PACKED = 1 << 30, 2_000_000
_PACKED = "v binary, d binary, nbr binary"


def _name(v: str, kinds: str) -> Column:
    """Name of a numbered vertex: the letter of its kind and its key."""
    return F.concat(F.element_at(F.array(*map(F.lit, kinds)), F.expr(f"cast({v} & 7 as int) + 1")), F.expr(f"cast(shiftright({v}, 3) as string)"))


def _by_name(v: np.ndarray, kinds: str) -> list[np.ndarray]:
    """Keys for ``np.lexsort`` that order numbered vertices as their names are ordered."""
    key = v >> 3
    size = np.abs(key)
    digits = np.searchsorted(10 ** np.arange(1, 18, dtype=np.int64), size, "right") + 1
    return [digits.astype(np.int8), size * 10 ** (18 - digits), np.frombuffer(kinds.encode().ljust(8), np.uint8)[v & 7].astype(np.int16) * 2 + (key >= 0)]


def _first_numbered(both: DataFrame, n: int, kinds: str, walkers: int, seed: int, start: str) -> list[int]:
    """``_start``, of numbered edges in both directions. Only keys below a bound are made distinct and ordered; it
    rises until enough are found."""
    key = random_key(seed, F.lit("start"), *(_name(c, kinds) for c in (("src",) if start == "uniform" else ("src", "dst"))))
    share = walkers * 100 / max(1, n)
    while True:
        rows = both.select(key.alias("key"), "src") if share >= 1 else both.select(key.alias("key"), "src").where(F.col("key") < f"{int(share * 2**128):032x}")
        found = rows.distinct().orderBy("key", _name("src", kinds)).limit(walkers).collect()  # ``walkers`` rows
        if len(found) == walkers or share >= 1:
            return [x.src for x in found]
        share *= 30


def _walk_packed(edges: DataFrame, kinds: str, m: float, seed: int, walkers: int, start: str, steps: int | None, most: int = MOST_PACKED) -> DataFrame:
    """Neighbours are made distinct, ordered by name and packed by tasks, each for some vertices. One task writes them as they come to
    a file of its own, holds where each vertex has its own, and walks: a step of a walker is a look into the file."""
    spark = ship(edges.sparkSession)
    way = lambda x, y: F.struct(F.col(x).alias("src"), F.col(y).alias("dst"))
    both = edges.where("src <> dst").select(F.explode(F.array(way("src", "dst"), way("dst", "src"))).alias("e")).select("e.src", "e.dst")
    n = both.count()
    if n > most:
        return walk(cut(both.select(_name("src", kinds).alias("src"), _name("dst", kinds).alias("dst")).distinct()), m, seed, walkers, start, steps)
    first = _first_numbered(both, n, kinds, walkers, seed, start)

    def pack(batches):
        parts = [(b.column("src").to_numpy(), b.column("dst").to_numpy()) for b in batches if b.num_rows]
        if parts:
            src, dst = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.lexsort([*_by_name(dst, kinds), src])
            src, dst = src[order], dst[order]
            new = np.append(True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1]))
            src, dst = src[new], dst[new]
            at = np.flatnonzero(np.append(True, src[1:] != src[:-1]))
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.binary()) for x in (coloured.put(src[at]), coloured.put(np.diff(np.append(at, len(src)))), coloured.put(dst))], names=["v", "d", "nbr"])

    def run(batches):
        vs, ds = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        with tempfile.TemporaryFile() as file:
            wide = []  # where each packed row begins in the file, its first edge, whether its numbers take four bytes
            edges = 0
            for b in batches:
                for v, d, nbr in zip(*(b.column(c) for c in ("v", "d", "nbr")), strict=True):
                    vs.append(coloured.get(v.as_py()).astype(np.int64))
                    ds.append(coloured.get(d.as_py()).astype(np.int64))
                    own = coloured.get(nbr.as_py())
                    wide.append((edges, file.tell(), own.dtype))
                    edges += len(own)
                    file.write(own.data)
            file.flush()
            v, d = np.concatenate(vs), np.concatenate(ds)
            lists = _Packed(file, v, d, wide)
            each = max(3, -(-(steps or steps_for(len(v), m)) // walkers))
            name = lambda x: None if x is None else f"{kinds[x & 7]}{x >> 3}"
            for w, at in enumerate(first):
                path, degree = [], []
                for t in range(1, each + 1):
                    path.append(at)
                    degree.append(lists.degree(at))
                    at = lists.one(at, int(hashlib.md5(f"{seed}|{w}|{t}".encode()).hexdigest()[:8], 16) % degree[-1])
                closed = [None] + [int(lists.linked(x, y)) for x, y in zip(path, path[2:], strict=False)] + [None]
                names = [name(x) for x in path]
                columns = [[w] * each, list(range(1, each + 1)), names, degree, [None, *names[:-1]], [*names[1:], None], closed]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int32()), strict=True)], names=[f.split()[0] for f in _STEPS.split(", ")])

    packed = both.repartition(max(spark.sparkContext.defaultParallelism, -(-n // PACKED)), "src").mapInArrow(pack, _PACKED)
    return cut(packed.repartition(1).mapInArrow(run, _STEPS))  # some rows for each walker


class _Packed:
    """Neighbours of numbered vertices, by name, in an open file."""

    def __init__(self, file, v: np.ndarray, d: np.ndarray, rows: list[tuple[int, int, np.dtype]]):
        self.file, self.rows, self.first = file, rows, [x[0] for x in rows]
        order = np.argsort(v)
        self.v, self.d, self.at = v[order], d[order], (np.cumsum(d) - d)[order]

    def _place(self, v: int) -> int:
        return int(np.searchsorted(self.v, v))

    def degree(self, v: int) -> int:
        return int(self.d[self._place(v)])

    def _read(self, edge: int, n: int) -> np.ndarray:
        start, begin, kind = self.rows[bisect.bisect_right(self.first, edge) - 1]
        self.file.seek(begin + (edge - start) * kind.itemsize)
        return np.frombuffer(self.file.read(n * kind.itemsize), kind)

    def one(self, v: int, i: int) -> int:
        return int(self._read(int(self.at[self._place(v)]) + i, 1)[0])

    def linked(self, u: int, v: int) -> bool:
        """Looked for among the neighbours of the end that has fewer."""
        u, v = (u, v) if self.degree(u) <= self.degree(v) else (v, u)
        i = self._place(u)
        return bool((self._read(int(self.at[i]), int(self.d[i])) == v).any())


#: Neighbours of a vertex that a look-up brings to the driver at most.
MOST_NEAR = 200_000


def walk_by(near: Callable[[list[str]], DataFrame], vertices: DataFrame, m: float = 1.0, seed: int = 0, steps: int | None = None, most: int = MOST_NEAR) -> DataFrame:
    """The steps of ``walk`` with one walker from a uniform start, over a graph that is only looked up: ``near`` gives the edges
    (v, nbr) of some vertices, ``vertices`` has each v once. Of the graph nothing is sorted, written or sent but neighbours
    of the vertices where the walker stands."""
    spark = vertices.sparkSession
    found = vertices.agg(F.count(F.lit(1)).alias("n"), F.min(F.struct(random_key(seed, F.lit("start"), "v").alias("key"), "v")).alias("first")).first()
    path, degree, lists, closed = [found.first.v] if found.n else [], [], [], [None]
    for t in range(1, 1 + max(3, steps or steps_for(found.n, m)) * len(path)):
        own = near(path[-1:]).select("nbr")
        few = sorted(r.nbr for r in own.limit(most + 1).collect())
        d = len(few) if len(few) <= most else own.count()
        i = int(hashlib.md5(f"{seed}|0|{t}".encode()).hexdigest()[:8], 16) % d
        degree.append(d)
        lists = [*lists[-1:], few if d == len(few) else None]
        path.append(few[i] if d == len(few) else own.select("nbr", F.row_number().over(Window.orderBy("nbr")).alias("i")).where(F.col("i") == i + 1).first().nbr)
        if t > 1:
            before, after = path[-3], path[-1]
            closed.append(int(after in lists[0] if lists[0] is not None else not near([before]).where(F.col("nbr") == after).isEmpty()))
    path = path[: len(degree)]
    rows = [(0, t + 1, v, degree[t], path[t - 1] if t else None, path[t + 1] if t + 1 < len(path) else None, closed[t] if t + 1 < len(path) else None) for t, v in enumerate(path)]
    return spark.createDataFrame(rows, _STEPS)


def wedges(steps: DataFrame, edges: DataFrame) -> DataFrame:
    """Each step with degree, and for interior ones whether the vertices before and after it are linked."""
    if "closed" in steps.columns:
        return steps
    w = Window.partitionBy("walker").orderBy("step")
    near = steps.withColumn("before", F.lag("v").over(w)).withColumn("after", F.lead("v").over(w))
    with_d = near.join(degrees(edges), "v")
    closed = edges.select(F.col("src").alias("before"), F.col("dst").alias("after"), F.lit(1).alias("closed"))
    return with_d.join(closed, ["before", "after"], "left").select("walker", "step", "v", "d", "before", "after", F.when(F.col("before").isNotNull() & F.col("after").isNotNull(), F.coalesce("closed", F.lit(0))).alias("closed"))


def estimate(steps: DataFrame, edges: DataFrame, kind: str = "local") -> DataFrame:
    """Ratio of the mean over interior steps of closed/(d - 1) to the mean over steps of 1/d; ``global``: closed wedges
    weighted by d over sums of d - 1, from the same steps."""
    w = wedges(steps, edges)
    if kind == "global":
        top, low = F.avg(F.when(F.col("closed").isNotNull(), F.col("closed") * F.col("d"))), F.avg((F.col("d") - 1).cast("double"))
    else:
        top, low = F.avg(F.when(F.col("closed").isNotNull(), F.when(F.col("d") > 1, F.col("closed") / (F.col("d") - 1)).otherwise(0.0))), F.avg(1 / F.col("d"))
    return w.agg(top.alias("top"), low.alias("low"), F.count(F.lit(1)).alias("steps")).select("steps", (F.col("top") / F.col("low")).alias("value"))


def one_shot(edges: DataFrame, r: int, seed: int = 0) -> DataFrame:
    """The same ratio from r independent draws of the walk's steady state: a directed edge gives the centre (so by
    degree), and two uniform neighbours of it, each by least key, are before and after."""
    slots = edges.withColumn("key", random_key(seed, "src", "dst")).orderBy("key", "src", "dst").limit(r).select(F.concat_ws(">", "src", "dst").alias("slot"), F.col("src").alias("c"))
    seen = F.broadcast(slots).join(edges, F.col("c") == F.col("src"))
    pick = lambda side: F.min_by("dst", F.struct(random_key(seed, F.lit(side), "slot", "dst"), "dst"))
    drawn = seen.groupBy("slot", "c").agg(pick("l").alias("a"), pick("r").alias("b"), F.count(F.lit(1)).alias("d"))
    closing = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(1).alias("closed"))
    w = drawn.join(closing, ["a", "b"], "left")
    top = F.avg(F.when(F.col("d") > 1, F.coalesce("closed", F.lit(0)) / (F.col("d") - 1)).otherwise(0.0))
    return w.agg((top / F.avg(1 / F.col("d"))).alias("value"), F.count(F.lit(1)).alias("steps"))


def normalise(value: Column, how: str = "clip") -> Column:
    """``clip`` to [0, 1], or its ``complement``."""
    clipped = F.least(F.lit(1.0), F.greatest(F.lit(0.0), value))
    return clipped if how == "clip" else 1.0 - clipped


def connected(edges: DataFrame) -> DataFrame:
    """v, component (least vertex of it): labels spread and jump until none changes."""
    edges = cut(edges)
    label = cut(edges.groupBy(F.col("src").alias("v")).agg(F.min("dst").alias("m")).select("v", F.least("v", "m").alias("component")))
    while True:
        near = edges.join(label.select(F.col("v").alias("src"), "component"), "src").groupBy(F.col("dst").alias("v")).agg(F.min("component").alias("near"))
        new = label.join(near, "v").select("v", F.least("component", "near").alias("component"), F.col("component").alias("old"))
        jump = new.select(F.col("v").alias("component"), F.col("component").alias("far"))
        new = cut(new.join(jump, "component").select("v", F.least("component", "far").alias("component"), "old"))
        if new.where("component <> old").isEmpty():
            return new.select("v", "component")
        label = new.select("v", "component")


def pagerank(edges: DataFrame, damping: float = 0.85, iterations: int = 10, every: int = 5) -> DataFrame:
    """v, rank; ranks sum to the number of vertices. Undirected edges, so there are no sinks."""
    d = degrees(edges)
    links = cut(edges.join(d.withColumnRenamed("v", "src"), "src"))
    rank = d.select("v", F.lit(1.0).alias("rank"))
    for i in range(1, iterations + 1):
        sent = links.join(rank.withColumnRenamed("v", "src"), "src").groupBy(F.col("dst").alias("v")).agg(F.sum(F.col("rank") / F.col("d")).alias("got"))
        rank = sent.select("v", (F.lit(1 - damping) + damping * F.col("got")).alias("rank"))
        if i % every == 0:
            rank = cut(rank)
    return rank
