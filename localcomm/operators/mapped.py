"""A graph as sorted arrays in files of the shared folder, mapped into memory by every task that walks, ranks or sweeps on it.

Nothing of the graph passes through the driver but a row for each part of it, and the tasks of one machine share its pages.
Vertices go by their place in the sorted order. Needs a shared folder with a local path (`possible`); elsewhere callers join tables.

Cases: a seed without edges stands alone; parts written by lost attempts have names of their own and are never read.
"""

from __future__ import annotations

import os
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.functions.sets import PRIME
from localcomm.operators import ranking
from localcomm.operators.graph import both_ways, unit_weight
from localcomm.params import Derived, Params
from localcomm.plans.stages import shared_root, staged

#: Edges from which a graph is mapped rather than sent to all tasks.
MAP_FROM = 300_000
#: Rows (edges, both ways) of a part that a task sorts and writes.
PART_ROWS = 500_000
#: Rows that a whole graph's ranking step takes at a time.
STEP_ROWS = 1_000_000
#: Rows of a component up to which it is ranked as a graph of its own.
OWN_ROWS = 2 * ranking.LOCAL_MOST
_PART = {"node": np.int64, "size": np.int64, "deg": np.float64, "dst": np.int64, "w": np.float64, "hi": np.int64}
#: Distinct weights up to which a row holds the number of its weight.
CODES = 1 << 16
#: Rows on either side of a draw's share of them that are looked at first.
NEAR = 16
#: Edges that a task deals out at a time.
DEAL_ROWS = 500_000


@dataclass(frozen=True)
class Layout:
    """Where a mapped graph lies, its vertices and its rows; a `unit` one takes all its weights as 1, a `coded` one holds numbers of weights."""

    folder: str
    n: int
    rows: int
    unit: bool = False
    coded: bool = False

    @property
    def kinds(self) -> dict[str, type]:
        """Types of the arrays: places in 4 bytes where they fit, and running weights, which draws need below 2^32."""
        return {"node": np.int64, "end": np.int64, "deg": np.float64, "dst": self.place, "w": np.uint16 if self.coded else np.float64, "hi": np.uint32}

    @property
    def place(self) -> type:
        return np.int32 if self.n < 1 << 31 else np.int64


def local_path(spark: SparkSession) -> str | None:
    """The shared folder as a path of the machine, or None if it lies on another kind of file system."""
    root = shared_root(spark)
    if root.startswith("file:"):
        return "/" + root[len("file:") :].lstrip("/")
    return root if root.startswith("/") and spark.sparkContext._jsc.hadoopConfiguration().get("fs.defaultFS", "file:///").startswith("file:") else None


def wanted(spark: SparkSession, p: Params, m: int) -> bool:
    """Whether a graph of m edges is to be mapped."""
    return p.engine == "auto" and m > MAP_FROM and local_path(spark) is not None


def layout(edges: DataFrame, weighted: bool = True) -> Layout:
    """The files of a graph with columns src, dst and w, written once for each table that a caller holds."""
    known = edges.__dict__.setdefault("_layouts", {})
    if weighted not in known:
        twin = edges.__dict__.get("_weighted_twin")
        shared = twin.__dict__.get("_layouts", {}).get(True) if twin is not None else None
        known[weighted] = replace(shared, unit=True) if shared else _written(edges, weighted)
    return known[weighted]


def twins(plain: DataFrame, weighted: DataFrame) -> None:
    """Tell that a graph of weights 1 has the very edges of a weighted one, whose files it can then share."""
    plain.__dict__["_weighted_twin"] = weighted


def kept(edges: DataFrame, of: DataFrame, keep) -> None:
    """Map `edges`, the part of the mapped graph `of` that `keep` (of arrays src < dst) tells, from the files of `of`.

    `keep` and the condition that made `edges` must agree; the number of rows is compared.
    """
    spark, where = edges.sparkSession, layout(of)
    folder, tasks = new_folder(spark), max(1, -(-where.rows // PART_ROWS))

    def write(frames):
        for f in frames:
            g = opened(where)
            for i in f["id"].tolist():
                low, high = (int(np.searchsorted(g.end, where.rows * j // tasks)) if j < tasks else g.n for j in (i, i + 1))
                if low == high:
                    continue
                at = np.arange(low, high)
                begun, stop = int(g.first(at[:1])[0]), int(g.end[high - 1])
                size = np.diff(np.append(begun, g.end[low:high]))
                src, dst, hi = np.repeat(g.node[low:high], size), g.node[g.dst[begun:stop]], g.hi[begun:stop].astype(np.int64)
                wi = np.diff(hi, prepend=0)
                wi[np.cumsum(size) - size] = hi[np.cumsum(size) - size]
                mine = keep(np.minimum(src, dst), np.maximum(src, dst))
                if mine.any():
                    yield pd.DataFrame([_part_written(folder, src[mine], dst[mine], g.w[begun:stop][mine], wi[mine])], columns=["name", "low", "n", "rows"])

    held = spark.range(tasks, numPartitions=tasks).mapInPandas(write, HELD).collect()  # a row for each part
    found = _placed(spark, folder, held)
    if found.rows != 2 * edges.count():
        raise ValueError(f"{found.rows} rows were kept for twice {edges.count()} edges")
    edges.__dict__.setdefault("_layouts", {})[True] = found


def new_folder(spark: SparkSession, name: str = "mapped") -> str:
    return f"{local_path(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


HELD = "name string, low long, n long, rows long"


def _part_written(folder: str, src: np.ndarray, dst: np.ndarray, w: np.ndarray, wi: np.ndarray) -> tuple[str, int, int, int]:
    """Write the rows of some vertices, sorted by src and dst; the part's name, smallest vertex, vertices and rows."""
    node, first = np.unique(src, return_index=True)
    size = np.diff(np.append(first, len(src)))
    run = np.cumsum(wi)
    hi = run - np.repeat(run[first] - wi[first], size)
    os.makedirs(folder, exist_ok=True)
    name = uuid.uuid4().hex
    for key, values in (("node", node), ("size", size), ("deg", np.add.reduceat(w, first)), ("dst", dst), ("w", w), ("hi", hi)):
        values.astype(_PART[key]).tofile(f"{folder}/{name}.{key}")
    return name, int(node[0]), len(node), len(src)


def told(name: str, low: int, n: int, rows: int):
    """What a task says of the part it has written."""
    import pyarrow as pa

    return pa.RecordBatch.from_pydict({"name": [name], "low": [low], "n": [n], "rows": [rows]}, pa.schema([("name", pa.string()), ("low", pa.int64()), ("n", pa.int64()), ("rows", pa.int64())]))


def gathered(spark: SparkSession, folder: str, held: list, kinds: dict[str, type], by_row: set[str]) -> None:
    """Parts of sorted arrays, put in one file for each; the running numbers `end` go on from part to part."""
    held = sorted(held, key=lambda r: r["low"])
    n, total = sum(r["n"] for r in held), sum(r["rows"] for r in held)
    os.makedirs(folder, exist_ok=True)
    for key, kind in kinds.items():
        with open(f"{folder}/{key}", "wb") as f:
            f.truncate(np.dtype(kind).itemsize * (total if key in by_row else n))
    at = np.cumsum([0] + [r["n"] for r in held]).tolist()
    begun = np.cumsum([0] + [r["rows"] for r in held]).tolist()
    names = [r["name"] for r in held]

    def place(frames):
        for f in frames:
            for i in f["id"].tolist():
                for key, kind in kinds.items():
                    values = np.fromfile(f"{folder}/{names[i]}.{key}", kind)
                    _put(f"{folder}/{key}", begun[i] if key in by_row else at[i], values + begun[i] if key == "end" else values)
                yield pd.DataFrame({"id": [i]})

    if names:
        assert spark.range(len(names), numPartitions=len(names)).mapInPandas(place, "id long").count() == len(names)
    for name in names:
        for key in kinds:
            os.unlink(f"{folder}/{name}.{key}")


def _put(path: str, at: int, values: np.ndarray) -> None:
    with open(path, "r+b") as out:
        out.seek(values.dtype.itemsize * at)
        out.write(np.ascontiguousarray(values).data)


def _vertices(edges: DataFrame, folder: str) -> tuple[int, int]:
    """Write all vertices, sorted, and where the rows of each end; how many vertices and rows there are."""
    ends = staged(both_ways(edges.select("src", "dst")).groupBy("src").agg(F.count(F.lit(1)).alias("size")), "vertices")
    n, rows = ends.agg(F.count(F.lit(1)), F.sum("size")).first()

    def write(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        src, size = (np.concatenate([b.column(c).to_numpy() for b in got]) for c in ("src", "size"))
        order = np.argsort(src)
        os.makedirs(folder, exist_ok=True)
        name = uuid.uuid4().hex
        src[order].tofile(f"{folder}/{name}.node")
        np.cumsum(size[order]).tofile(f"{folder}/{name}.end")
        yield told(name, int(src[order][0]), len(src), int(size.sum()))

    held = ends.repartitionByRange(max(1, -(-n // PART_ROWS)), "src").mapInArrow(write, HELD).collect()  # a row for each part
    gathered(edges.sparkSession, folder, held, {"node": np.int64, "end": np.int64}, set())
    return n, rows or 0


def _weights(edges: DataFrame, weighted: bool) -> tuple[np.ndarray, np.ndarray] | None:
    """The distinct weights, sorted, and their whole numbers; None beyond CODES."""
    if edges.agg(F.approx_count_distinct("w")).first()[0] > 1.2 * CODES:
        return None
    held = edges.groupBy("w").agg(F.first(unit_weight(weighted)).alias("wi")).limit(CODES + 1).toPandas().sort_values("w")  # at most so many rows
    return (held["w"].to_numpy(), held["wi"].to_numpy()) if len(held) <= CODES and held["w"].notna().all() else None


def _written(edges: DataFrame, weighted: bool) -> Layout:
    """The files of a graph. Tasks deal rows out to ranges of vertices, packed, and other tasks sort a range and write it in its place.

    Vertices and the ends of their rows are written before, so that there is one copy of the rows; a range that is written again gets the same bytes.
    """
    spark = edges.sparkSession
    folder = new_folder(spark)
    n, total = _vertices(edges, folder)
    codes = _weights(edges, weighted)
    where = Layout(folder, n, total, coded=codes is not None)
    for key, kind in where.kinds.items():
        if key not in ("node", "end"):
            with open(f"{folder}/{key}", "wb") as f:
                f.truncate(np.dtype(kind).itemsize * (n if key == "deg" else total))
    if codes is not None:
        codes[0].astype(np.float64).tofile(f"{folder}/weights")
        codes[1].astype(np.int64).tofile(f"{folder}/units")
    if not total:
        return where
    tasks = max(1, -(-total // PART_ROWS))
    kinds = [where.place, where.place, where.kinds["w"], *([] if where.coded else [np.int64])]
    load = lambda key, kind: np.asarray(np.memmap(f"{folder}/{key}", kind, "r"))

    def deal(batches):
        import pyarrow as pa

        node, end = load("node", np.int64), load("end", np.int64)
        lows = np.searchsorted(end, total * np.arange(tasks) // tasks, side="right")
        schema = pa.schema([("range", pa.int64()), ("rows", pa.int64()), ("packed", pa.binary())])
        for src, dst, w, *wi in _taken(batches, DEAL_ROWS):
            a, b = np.searchsorted(node, src).astype(where.place), np.searchsorted(node, dst).astype(where.place)
            w = np.searchsorted(load("weights", np.float64), w).astype(np.uint16) if where.coded else w
            columns = [np.concatenate([a, b]), np.concatenate([b, a]), *(np.concatenate([x, x]) for x in (w, *wi))]
            mine = np.searchsorted(lows, columns[0], side="right") - 1
            order = np.argsort(mine, kind="stable")
            columns, mine = [x[order] for x in columns], mine[order]
            cuts = np.append(np.flatnonzero(np.diff(mine, prepend=-1)), len(mine))
            packed = [b"".join(x[i:j].tobytes() for x in columns) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(mine[cuts[:-1]]), pa.array(np.diff(cuts)), pa.array(packed, pa.binary())], schema=schema)

    def place(batches):
        import pyarrow as pa

        end, got = load("end", np.int64), {}
        for batch in batches:
            for i, rows, packed in zip(*(batch.column(c).to_pylist() for c in ("range", "rows", "packed")), strict=True):
                got.setdefault(i, []).append((rows, packed))
        done = 0
        for blocks in got.values():
            a, b, w, *wi = (np.concatenate(x) for x in zip(*(_unpacked(packed, rows, kinds) for rows, packed in blocks), strict=True))
            order = np.argsort(a.astype(np.int64) * n + b, kind="stable")
            a, b, w, *wi = (x[order] for x in (a, b, w, *wi))
            units, weights = (load("units", np.int64)[w], load("weights", np.float64)[w]) if where.coded else (wi[0], w)
            first = np.flatnonzero(np.diff(a, prepend=-1))
            begun = int(end[a[0] - 1]) if a[0] else 0
            if int(end[a[-1]]) - begun != len(a):
                raise ValueError(f"{len(a)} rows from {begun} to {end[a[-1]]}")
            run = np.cumsum(units)
            hi = run - np.repeat(run[first] - units[first], np.diff(np.append(first, len(a))))
            if hi.max() >= 1 << 32:
                raise ValueError("a vertex with a total weight of 2^32 thousandths or more")
            for key, at, values in (("deg", int(a[0]), np.add.reduceat(weights, first)), ("dst", begun, b), ("w", begun, w), ("hi", begun, hi)):
                _put(f"{folder}/{key}", at, values.astype(where.kinds[key]))
            done += len(a)
        yield pa.RecordBatch.from_pydict({"rows": [done]}, pa.schema([("rows", pa.int64())]))

    asked = edges.select("src", "dst", F.col("w").cast("double").alias("w"), *([] if where.coded else [unit_weight(weighted).alias("wi")]))
    dealt = asked.mapInArrow(deal, "range long, rows long, packed binary").repartition(tasks, "range")
    done = dealt.mapInArrow(place, "rows long").agg(F.sum("rows")).first()[0]
    assert done == total
    return where


def _taken(batches, most: int):
    """The columns of some batches, put together up to about so many rows."""
    got, many = [], 0
    for batch in batches:
        got.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
        many += batch.num_rows
        if many >= most:
            yield [np.concatenate(x) for x in zip(*got, strict=True)]
            got, many = [], 0
    if many:
        yield [np.concatenate(x) for x in zip(*got, strict=True)]


def _unpacked(packed: bytes, rows: int, kinds: list[type]) -> list[np.ndarray]:
    out, at = [], 0
    for kind in kinds:
        out.append(np.frombuffer(packed, kind, rows, at))
        at += rows * np.dtype(kind).itemsize
    return out


def _placed(spark: SparkSession, folder: str, held: list) -> Layout:
    """Parts, put in one file for each array, with places for vertices."""
    held = sorted(held, key=lambda r: r["low"])
    n, total = sum(r["n"] for r in held), sum(r["rows"] for r in held)
    os.makedirs(folder, exist_ok=True)
    where = Layout(folder, n, total)
    for key, kind in where.kinds.items():
        with open(f"{folder}/{key}", "wb") as f:
            f.truncate(np.dtype(kind).itemsize * (n if key in ("node", "end", "deg") else total))
    at, begun, places = 0, 0, []
    for r in held:
        places.append((r["name"], at, r["n"], begun, r["rows"]))
        at, begun = at + r["n"], begun + r["rows"]

    def place(frames):
        nodes = np.concatenate([_part(folder, name, "node") for name, *_ in places])
        for f in frames:
            for i in f["id"].tolist():
                name, at, n, begun, rows = places[i]
                for key, values in (
                    ("node", nodes[at : at + n]),
                    ("end", begun + np.cumsum(_part(folder, name, "size"))),
                    ("deg", _part(folder, name, "deg")),
                    ("dst", np.searchsorted(nodes, _part(folder, name, "dst"))),
                    ("w", _part(folder, name, "w")),
                    ("hi", _part(folder, name, "hi")),
                ):
                    _put(f"{folder}/{key}", at if key in ("node", "end", "deg") else begun, values.astype(where.kinds[key]))
                yield pd.DataFrame({"id": [i]})

    if places:
        done = spark.range(len(places), numPartitions=len(places)).mapInPandas(place, "id long").count()
        assert done == len(places)
    for name, *_ in places:
        for key in _PART:
            os.unlink(f"{folder}/{name}.{key}")
    return where


def _part(folder: str, name: str, key: str) -> np.ndarray:
    return np.fromfile(f"{folder}/{name}.{key}", _PART[key])


_open: dict[Layout, MappedGraph] = {}


def opened(where: Layout) -> MappedGraph:
    """The graph, mapped once in a worker; the one before is let go."""
    if where not in _open:
        _open.clear()
        _open[where] = MappedGraph(where)
    return _open[where]


class Coded:
    """Weights of rows that hold numbers of weights."""

    def __init__(self, code: np.ndarray, weight: np.ndarray):
        self.code, self.weight = code, weight

    def __getitem__(self, at) -> np.ndarray:
        return self.weight[self.code[at]]

    def tolist(self) -> list[float]:
        return self[:].tolist()


class MappedGraph:
    """A mapped graph in one task: walks, subgraphs, ranks and sweeps of a seed."""

    def __init__(self, where: Layout):
        self.n = where.n
        read = lambda key, kind: np.asarray(np.memmap(f"{where.folder}/{key}", kind, "r")) if where.rows else np.zeros(0, kind)
        self.node, self.end, self.deg, self.dst, self.w, self.hi = (read(key, kind) for key, kind in where.kinds.items())
        if where.coded:
            self.w = Coded(self.w, read("weights", np.float64))
        self.unit = where.unit
        if self.unit:
            self.deg, self.w = np.diff(self.end, prepend=0).astype(np.float64), np.broadcast_to(np.float64(1), where.rows)

    def at(self, seed: int) -> int:
        """The place of a vertex; -1 without edges."""
        i = int(np.searchsorted(self.node, seed))
        return i if i < self.n and self.node[i] == seed else -1

    def first(self, at: np.ndarray) -> np.ndarray:
        return np.where(at > 0, self.end[np.maximum(at - 1, 0)], 0)

    def moves(self, at: np.ndarray, u: np.ndarray) -> np.ndarray:
        """The next place of walkers by draws u: the first neighbour whose share ends beyond the draw."""
        low, high = self.first(at), self.end[at] - 1
        if self.unit:
            return self.dst[low + u * (high - low + 1) // PRIME]
        total = self.hi[high].astype(np.int64)
        want = u * total // PRIME
        # Where weights differ little a draw falls near its share of the rows, which mostly leaves a few to look at.
        guess = low + (want * ((high - low) / np.maximum(total, 1))).astype(np.int64)
        left, right = np.maximum(guess - NEAR, low), np.minimum(guess + NEAR, high)
        before, until = self.hi[left] > want, self.hi[right] > want
        low, high = np.where(before, low, np.where(until, left, right) + 1), np.where(before, left, np.where(until, right, high))
        while len(some := np.flatnonzero(low < high)):
            a, b = low[some], high[some]
            mid = (a + b) >> 1
            beyond = self.hi[mid] > want[some]
            low[some], high[some] = np.where(beyond, a, mid + 1), np.where(beyond, mid, b)
        return self.dst[low].astype(np.int64)

    def visited(self, seed: int, walks: np.ndarray, p: Params) -> tuple[np.ndarray, np.ndarray]:
        """Vertices that the trials of a seed visit and the number of trials that visit each."""
        from localcomm.operators.walks import walked

        start = self.at(seed)
        if start < 0:
            return np.array([seed], np.int64), np.array([len(walks)], np.int64)
        place, hits = walked(self, seed, walks, p, start)
        return self.node[place], hits

    def rows_of(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row numbers of the edges of some places, and how many each has."""
        first = self.first(at)
        size = self.end[at] - first
        return np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum()), size

    def compact(self, at: np.ndarray) -> ranking.Compact:
        """The graph that some places (ascending) induce, with their full degrees."""
        rows, size = self.rows_of(at)
        src, dst = np.repeat(at, size), self.dst[rows]
        both = np.isin(dst, at)
        src, dst, rows = src[both], dst[both], rows[both]
        return ranking.Compact(self.node[src], self.node[dst], self.w[rows], self.deg[src])

    def relevant(self, seed: int, n: int, p: Params) -> np.ndarray:
        """Vertices of a seed's subgraph by walks and relevance, for a graph of n vertices with isolated ones."""
        from localcomm.operators.walks import relevant_mask

        node, hits = self.visited(seed, np.arange(p.n_w, dtype=np.int64), p)
        return node[relevant_mask(node, hits, seed, n, p)]

    def partition(self, key: int, seed: int, n: int, p: Params, d: Derived, total: float) -> pd.DataFrame:
        """CURVE rows of a seed: walks, relevance, subgraph, rank and sweep; `key` is what the rows call it."""
        node = self.relevant(seed, n, p)
        at = np.searchsorted(self.node, node) if self.at(seed) >= 0 else np.zeros(0, np.int64)
        return self.compact(at).curve(key, seed, p, d, total)

    def component(self, at: int) -> np.ndarray | None:
        """All places that edges lead to, ascending; None beyond OWN_ROWS rows."""
        seen, edge, rows = np.array([at]), np.array([at]), 0
        while len(edge):
            mine, size = self.rows_of(edge)
            rows += int(size.sum())
            if rows > OWN_ROWS:
                return None
            edge = np.setdiff1d(self.dst[mine], seen)
            seen = np.union1d(seen, edge)
        return seen

    @cached_property
    def spans(self) -> list[tuple[int, int]]:
        """Places whose rows are taken at a time, STEP_ROWS or one vertex's."""
        out, at = [], 0
        while at < self.n:
            begun = int(self.end[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(self.end, begun + STEP_ROWS, side="right")))
            out.append((at, to))
            at = to
        return out

    def arriving(self, q: np.ndarray, each=map) -> np.ndarray:
        """What all vertices send each by weight; `each` maps over the spans, in threads if a caller has some."""
        y, out = q / self.deg, np.empty(self.n)

        def one(span: tuple[int, int]) -> None:
            at, to = span
            begun, stop = int(self.end[at - 1]) if at else 0, int(self.end[to - 1])
            come = y.take(self.dst[begun:stop])
            first = np.append(0, self.end[at : to - 1] - begun)
            out[at:to] = np.add.reduceat(come if self.unit else np.multiply(self.w[begun:stop], come, out=come), first)

        for _ in each(one, self.spans):
            pass
        return out

    def curve(self, key: int, seed: int, p: Params, d: Derived, total: float, threads: int = 1) -> pd.DataFrame:
        """`ranking.Compact.curve` on the whole graph: its component's if that is small, else by steps over all rows, in some threads."""
        at = self.at(seed)
        if at < 0:
            return ranking.no_curve()
        own = self.component(at)
        if own is not None and p.cut_scope == "full":
            return self.compact(own).curve(key, seed, p, d, total)
        with ThreadPoolExecutor(threads) as pool:
            q, _ = ranking.ranked(lambda q: self.arriving(q, pool.map if threads > 1 else map), self.deg, at, p, d)
        if p.cut_scope == "subgraph":
            total = float(self.deg.sum())
        some = np.flatnonzero(q > 0)
        share = np.round(q[some] / self.deg[some], ranking.DIGITS)
        order = some[np.lexsort((some, -share))[: p.n_s]]
        rows, size = self.rows_of(order)
        src, dst = np.repeat(order, size), self.dst[rows]
        both = np.isin(dst, order)
        by = np.sort(order)
        small = lambda x: np.searchsorted(by, x)
        return ranking.swept(key, self.node[by], q[by], np.round(q[by] / self.deg[by], ranking.DIGITS), self.deg[by], small(order), small(src[both]), small(dst[both]), self.w[rows[both]], p, total)


def whole_curves(edges: DataFrame, seeds: DataFrame, scenarios: ranking.Scenarios, total: float) -> DataFrame:
    """`ranking.whole_curves` on a mapped graph."""
    where, seeds = layout(edges), seeds.select("seed").distinct()
    # Few seeds leave cores idle, which their steps can take.
    slots = int(edges.sparkSession.sparkContext.defaultParallelism) // max(1, seeds.count())

    def job(frames):
        threads = max(1, min(slots, os.cpu_count() or 1))
        for f in frames:
            for key in f["seed"].tolist():
                yield opened(where).curve(key, key % ranking.SCENARIO, *scenarios[key // ranking.SCENARIO], total, threads)

    return spread(seeds).mapInPandas(job, ranking.CURVE).replace(float("nan"), None)


def fused_curves(combined: DataFrame, seeds: DataFrame, n: int, scenarios: ranking.Scenarios, total: float) -> DataFrame:
    """`partition.fused_curves` on a mapped graph, for a grid of parameters: seeds go by `ranking.scenario_seeds`."""
    where = layout(combined, scenarios[0][0].weighted)

    def job(frames):
        for f in frames:
            for key in f["seed"].tolist():
                yield opened(where).partition(key, key % ranking.SCENARIO, n, *scenarios[key // ranking.SCENARIO], total)

    return spread(_distinct(seeds)).mapInPandas(job, ranking.CURVE).replace(float("nan"), None)


def relevant_sizes(combined: DataFrame, seeds: DataFrame, n: int, scenarios: ranking.Scenarios) -> DataFrame:
    """seed, count: vertices of each seed's subgraph; seeds go by `ranking.scenario_seeds`."""
    where = layout(combined, scenarios[0][0].weighted)

    def job(frames):
        for f in frames:
            for key in f["seed"].tolist():
                yield pd.DataFrame({"seed": [key], "count": [len(opened(where).relevant(key % ranking.SCENARIO, n, scenarios[key // ranking.SCENARIO][0]))]})

    return spread(_distinct(seeds)).mapInPandas(job, "seed long, count long")


def _distinct(seeds: DataFrame) -> DataFrame:
    return seeds.select(F.col("seed").cast("long").alias("seed")).where("seed IS NOT NULL").distinct()


def spread(seeds: DataFrame, *by: str) -> DataFrame:
    """Seeds dealt over the tasks of a whole stage: a few rows are much work, so small partitions must not be put together."""
    return seeds.repartition(max(1, int(seeds.sparkSession.sparkContext.defaultParallelism) * 4), *(by or ("seed",)))


def visits(combined: DataFrame, seeds: DataFrame, p: Params, walks_a_task: int) -> DataFrame:
    """seed, node, hits: trials that visit the node, on a mapped graph."""
    where, tasks = layout(combined, p.weighted), -(-p.n_w // walks_a_task)
    chunks = seeds.select("seed", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("chunk"))
    chunks = spread(chunks, "seed", "chunk")

    def job(frames):
        for f in frames:
            for seed, chunk in zip(f["seed"].tolist(), f["chunk"].tolist(), strict=True):
                node, hits = opened(where).visited(seed, np.arange(chunk * walks_a_task, min(p.n_w, (chunk + 1) * walks_a_task), dtype=np.int64), p)
                yield pd.DataFrame({"seed": seed, "node": node, "hits": hits})

    return chunks.mapInPandas(job, "seed long, node long, hits long").groupBy("seed", "node").agg(F.sum("hits").alias("hits"))
