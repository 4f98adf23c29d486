"""The engines over edges packed in blocks, for graphs above the kernel limit whose vertex state fits one process.

Edges stay on the executors, as arrays in blocks of consecutive vertices, written once and held in memory for
the passes; a pass sends them the vertex state and gets every vertex's destination, gain and whether it moves.
Only arrays of one value a vertex are in the driver, and only up to `state_limit` vertices; numbers of vertices
take four bytes, and what is sent or kept between passes as few as its values need. Scores, hashes and tie rules
are those of the kernel and of the DataFrames, so that all three give the same clusterings.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import degree_class_np, portable_hash_np
from ..sources import drop, settle
from . import kernel
from .options import Options

#: Stored edges of a block (a vertex with more has a block of its own), and of a worker's chunk before it is summed and sent.
BLOCK, CHUNK = 1 << 16, 1 << 20
#: Marks a vertex that is no candidate where others have their destination.
STAYS = -9


@dataclass
class Blocks:
    """ids are the vertices' original numbers (ascending); rows (block, lo, hi, deg, dst, w) hold the edges of vertices lo..hi-1 in both directions."""

    ids: np.ndarray
    weights: np.ndarray
    deg: np.ndarray
    rows: DataFrame
    num: int
    den: int
    b: np.ndarray | None = None

    def __post_init__(self):
        self.ids, self.weights = _narrow(self.ids), _narrow(self.weights)
        self.b = None if self.b is None else _narrow(self.b)

    @property
    def vw(self) -> np.ndarray:
        return _wide(self.weights)

    @property
    def n(self) -> int:
        return len(self.ids)

    @property
    def stored(self) -> int:
        return int(self.deg.sum())


def _starts(size: np.ndarray) -> np.ndarray:
    """The first vertex of every block of vertices with so many edges (at most), and the number of vertices."""
    before = np.cumsum(size) - size
    block = before // BLOCK
    first = np.flatnonzero(np.append(True, block[1:] != block[:-1])) if len(size) else np.zeros(0, int)
    return np.append(first, len(size))


def _narrow(x: np.ndarray) -> np.ndarray:
    most = max(int(x.max()), -int(x.min())) if len(x) else 0
    return x.astype(next(f"i{k}" for k in (1, 2, 4, 8) if most < 1 << (8 * k - 1)), copy=False)


def _wide(x: np.ndarray) -> np.ndarray:
    return x.astype(np.int64, copy=False)


def _each(n: int) -> np.ndarray:
    """Every vertex by itself."""
    return np.arange(n, dtype=np.int32)


def _summed(x, y, w, n: int):
    """Edges sorted by (x, y), those of a pair added up. Weights that fit beside their key are sorted with it."""
    low = np.int64(max(1, n - 1).bit_length())
    key = x << low | y
    if (key[1:] < key[:-1]).any():
        bits = np.int64(int(w.max()).bit_length())
        if w.min() >= 0 and int(key.max()).bit_length() + bits < 64:
            key = np.sort(key << bits | w)
            key, w = key >> bits, key & ((np.int64(1) << bits) - 1)
        else:
            order = np.argsort(key)
            key, w = key[order], w[order]
    at = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, int)
    return key[at] >> low, key[at] & ((np.int64(1) << low) - 1), np.add.reduceat(w, at) if len(at) else w[:0]


def _least(h, x, at):
    """Of every run of rows that begins at one of at: the x with the smallest hash, the smaller of equals."""
    return np.minimum.reduceat(h << np.int64(32) | x, at) & np.int64((1 << 32) - 1)


def _dealt(x, y, w, starts, n: int):
    """A batch (block, src, dst, w) of the edges for each block."""
    x, y, w = _summed(x, y, w, n)
    if not len(x):
        return
    block = np.searchsorted(starts, x, "right") - 1
    at = np.append(np.flatnonzero(np.append(True, block[1:] != block[:-1])), len(x))
    parts = [[a[i:j].tobytes() for i, j in zip(at[:-1], at[1:], strict=True)] for a in (x.astype("i4"), y.astype("i4"), _narrow(w))]
    yield pa.RecordBatch.from_arrays([pa.array(block[at[:-1]].astype("i4")), *[pa.array(p, pa.binary()) for p in parts]], names=["block", "src", "dst", "w"])


def _gathered(chunks, starts, n: int):
    """Edges that come in pieces, summed and dealt a chunk at a time."""
    held, many = [], 0
    for piece in chunks:
        held.append(piece)
        many += len(piece[0])
        if many >= CHUNK:
            yield from _dealt(*(np.concatenate(a) for a in zip(*held, strict=True)), starts, n)
            held, many = [], 0
    if held:
        yield from _dealt(*(np.concatenate(a) for a in zip(*held, strict=True)), starts, n)


def _merged(chunks: DataFrame, starts: np.ndarray, n: int, sent) -> tuple[DataFrame, np.ndarray]:
    """(rows of the blocks, written; degree of every vertex) from chunks of edges."""
    blocks = len(starts) - 1

    def merge(table):
        block, starts = table["block"][0].as_py(), sent.value["starts"]
        lo, hi = int(starts[block]), int(starts[block + 1])
        parts = [table[k].to_pylist() for k in ("src", "dst", "w")]
        x, y = (np.frombuffer(b"".join(p), "i4") for p in parts[:2])
        w = np.concatenate([_wide(np.frombuffer(w, f"i{4 * len(w) // len(x)}")) for x, w in zip(parts[0], parts[2], strict=True)])
        x, y, w = _summed(x, y, w, n)
        deg = np.bincount(x - lo, minlength=hi - lo)
        return pa.table({"block": pa.array([block], pa.int32()), "lo": pa.array([lo], pa.int32()), "hi": pa.array([hi], pa.int32()), "deg": pa.array([deg.astype("i4").tobytes()], pa.binary()), "dst": pa.array([y.astype("i4").tobytes()], pa.binary()), "w": pa.array([_narrow(w).tobytes()], pa.binary())})

    most = 2 * chunks.sparkSession.sparkContext.defaultParallelism
    few = max(1, min(-(-blocks // 2), most))  # a pass over a small graph takes as long as its tasks take to start
    parts = max(few, blocks // 8)
    rows = chunks.repartition(parts, "block").groupBy("block").applyInArrow(merge, "block int, lo int, hi int, deg binary, dst binary, w binary")
    rows = settle(rows, "blocks")
    deg = np.zeros(n, np.int32)
    for lo, hi, d in held(rows, few).map(lambda row: row[:3]).collect():
        deg[lo:hi] = np.frombuffer(d, "i4")
    return rows, deg


#: Runtime settings by which Spark cuts files into partitions.
OPEN_COST, LEAST_PARTS = "spark.sql.files.openCostInBytes", "spark.sql.files.minPartitionNum"


def held(rows: DataFrame, parts: int = 1) -> RDD:
    """The written blocks in the executors' memory, in partitions of about one size (some parts or more); what does not stay there is read again. They go when rows are dropped."""
    if not hasattr(rows, "_held"):
        spark = rows.sparkSession
        before = {k: spark.conf.get(k, None) for k in (OPEN_COST, LEAST_PARTS)}
        try:
            spark.conf.set(OPEN_COST, "0")  # the files are small: by their bytes alone
            spark.conf.set(LEAST_PARTS, str(parts))
            read = rows.select("lo", "hi", "deg", "dst", "w").rdd
        finally:
            for k, v in before.items():
                spark.conf.unset(k) if v is None else spark.conf.set(k, v)
        rows._held = read.map(tuple).persist(StorageLevel.MEMORY_ONLY)
    return rows._held


EDGES = "block int, src binary, dst binary, w binary"


def _column(table, name: str) -> np.ndarray:
    return table[name].to_numpy()


def degrees(g) -> DataFrame | None:
    """(id, vw, n) of all vertices with their numbers of stored edges, written; None where the graph was not made with them."""
    plain = getattr(g.vertices, "_constrained", (g.vertices,))[0]
    if hasattr(plain, "_degrees") and not hasattr(plain._degrees, "_scratch"):
        plain._degrees = settle(plain._degrees, "vertices")
    return getattr(plain, "_degrees", None)


def vertices_of(g) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(ids, weights, constraint clusters if there are any) of a WGraph, by ascending id."""
    has_b = "b" in g.vertices.columns
    known = None if has_b else degrees(g)
    got = (g.vertices if known is None else known).select("id", "vw", *(["b"] if has_b else [])).toArrow()
    ids = _column(got, "id")
    order = np.argsort(ids, kind="stable")
    return ids[order], _column(got, "vw")[order], dense(_column(got, "b")[order]) if has_b else None


def dense(labels: np.ndarray) -> np.ndarray:
    """Any labels as clusters under their smallest vertex."""
    _, first, where = np.unique(_narrow(labels), return_index=True, return_inverse=True)
    return first[where]


def keep(c: DataFrame, ids: np.ndarray, labels: np.ndarray) -> None:
    """Lets a written clustering be taken from memory by whoever has the same vertices."""
    c._labels = ids, labels


def array_of(c: DataFrame, ids: np.ndarray | None = None) -> np.ndarray:
    """A clustering (id, cid) in the order of the vertices, those of ids if it was kept for them."""
    if ids is not None and getattr(c, "_labels", (None,))[0] is ids:
        return c._labels[1]
    got = c.select("id", "cid").toArrow()
    return dense(_column(got, "cid")[np.argsort(_column(got, "id"), kind="stable")])


def packed(g) -> Blocks:
    """A WGraph with its edges in blocks. They are made once for its edges and go with their owner."""
    plain, inside = getattr(g.vertices, "_constrained", (g.vertices, None))
    if inside is not None and getattr(inside, "_labels", (None,))[0] is getattr(plain, "_arrays", (0,))[0]:
        (ids, vw), b = plain._arrays, inside._labels[1]
    elif hasattr(g.vertices, "_arrays"):
        (ids, vw), b = g.vertices._arrays, None
    else:
        ids, vw, b = vertices_of(g)
        ids, vw = _narrow(ids), _narrow(vw)
        if b is None:
            g.vertices._arrays = ids, vw  # the rounds of an iteration take the same vertices
    if not hasattr(g.edges, "_blocks"):
        n = len(ids)
        deg = np.zeros(n, np.int64)
        known = degrees(g)
        got = (g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")) if known is None else known.select("id", "n")).toArrow()
        deg[np.searchsorted(ids, _column(got, "id").astype(ids.dtype))] = _column(got, "n")
        starts = _starts(deg)
        del got, deg
        sent = g.edges.sparkSession.sparkContext.broadcast({"ids": ids, "starts": starts})

        def pack(batches):
            ids, starts = sent.value["ids"], sent.value["starts"]
            pieces = ((*(np.searchsorted(ids, t[k].to_numpy().astype(ids.dtype)) for k in ("src", "dst")), t["w"].to_numpy()) for t in batches)
            yield from _gathered(pieces, starts, n)

        g.edges._blocks = _merged(g.edges.select("src", "dst", "w").mapInArrow(pack, EDGES), starts, n, sent)
        sent.destroy()
    rows, deg = g.edges._blocks
    return Blocks(ids, vw, deg, rows, g.num, g.den, b)


def _opened(row) -> tuple:
    """(lo, hi, src, dst, w) of a block."""
    lo, hi, deg, dst, w = row
    dst = np.frombuffer(dst, "i4")
    src = np.repeat(np.arange(lo, hi), np.frombuffer(deg, "i4"))
    return lo, hi, src, dst, np.frombuffer(w, f"i{len(w) // max(1, len(dst)) or 1}").astype(np.int64)


def _rows(batches):
    for t in batches:
        yield from (_opened(r) for r in zip(*(t[k].to_pylist() for k in ("lo", "hi", "deg", "dst", "w")), strict=True))


def local(g: Blocks) -> kernel.Graph:
    """The graph in this process; only for graphs whose stored edges are below the kernel limit."""
    got = [x[2:] for x in _rows([g.rows.select("lo", "hi", "deg", "dst", "w").toArrow()])]
    src, dst, w = (np.concatenate([np.zeros(0, np.int64), *[x[i] for x in got]]).astype(np.int64) for i in range(3))
    return kernel.Graph(_wide(g.ids), g.vw, src, dst, w, g.num, g.den, None if g.b is None else _wide(g.b))


def _send(g: Blocks, **arrays):
    """A broadcast of vertex arrays, each in as few bytes as its values need: whoever multiplies them takes them as `_wide`."""
    return g.rows.sparkSession.sparkContext.broadcast({k: x if x.dtype == bool else _narrow(x) for k, x in arrays.items() if x is not None})


def over(g: Blocks, f, out: tuple, *sent) -> list:
    """f(a, lo, hi, src, dst, w) over every block on the executors: an array of one value a vertex for each type in out, for "+" the sum of the blocks' numbers."""

    def run(rows):
        a = {k: x for s in sent for k, x in s.value.items()}
        for row in rows:
            lo, hi, src, dst, w = _opened(row)
            got = f(a, lo, hi, src, dst, w)
            yield lo, hi, *[int(x) if kind == "+" else (x if kind == "?" else _narrow(x)).tobytes() for x, kind in zip(got, out, strict=True)]

    got = sorted(held(g.rows).mapPartitions(run).collect())
    all_ = [0 if kind == "+" else np.empty(g.n, kind) for kind in out]
    for lo, hi, *parts in got:
        for i, (part, kind) in enumerate(zip(parts, out, strict=True)):
            if kind == "+":
                all_[i] += part
            else:
                all_[i][lo:hi] = np.frombuffer(part, kind if kind == "?" else f"i{len(part) // (hi - lo)}")
    # vertices of blocks without an edge are in no row
    none = np.zeros(0, np.int64)
    for lo, hi in zip([0, *[r[1] for r in got]], [*[r[0] for r in got], g.n], strict=True):
        if lo < hi:
            a = {k: x for s in sent for k, x in s.value.items()}
            for i, x in enumerate(f(a, lo, hi, none, none, none)):
                if out[i] == "+":
                    all_[i] += int(x)
                else:
                    all_[i][lo:hi] = x
    return all_


def _within(a, src, dst, w):
    """The edges inside the constraint, if there is one."""
    if "b" not in a:
        return src, dst, w
    keep = a["b"][src] == a["b"][dst]
    return src[keep], dst[keep], w[keep]


def canonical(raw: np.ndarray, n: int) -> np.ndarray:
    """Labels below 2n as clusters under their smallest vertex."""
    low = np.zeros(2 * n, np.int32)
    low[raw[::-1]] = _each(n)[::-1]  # the last one stands: the smallest
    return low[raw]


def totals(g: Blocks, c: np.ndarray) -> np.ndarray:
    out = np.zeros(g.n, np.int64)
    np.add.at(out, c, g.vw)
    return out


def _hashed(ids: np.ndarray) -> np.ndarray:
    """The hash of every vertex, a piece at a time."""
    out = np.empty(len(ids), np.int32)
    for i in range(0, len(ids), CHUNK // 16):
        out[i : i + CHUNK // 16] = portable_hash_np(ids[i : i + CHUNK // 16], 0)
    return out


def _fixed(g: Blocks, b: np.ndarray | None):
    return _send(g, vw=g.weights, ids=g.ids, h=_hashed(g.ids), b=b)


def choose(g: Blocks, c: np.ndarray, t: np.ndarray, fixed, wanted) -> tuple[np.ndarray, np.ndarray, int]:
    """(destination or STAYS, its gain, sum of all own scores) as in the kernel; wanted(destination, its score, own score) has the candidates."""
    n, num, den = g.n, g.num, g.den

    def best(a, lo, hi, src, dst, w):
        src, dst, w = _within(a, src, dst, w)
        c, t, ids = a["c"], a["t"], a["ids"]
        v, x, k = _summed(src - lo, _wide(c[dst]), w, n)
        own = x == c[v + lo]
        k_own, to, s_to = np.zeros(hi - lo, np.int64), np.full(hi - lo, -2, np.int32), np.zeros(hi - lo, np.int64)
        k_own[v[own]] = k[own]
        v, x, k = v[~own], x[~own], k[~own]
        if len(v):
            s = den * k - num * _wide(a["vw"][v + lo]) * _wide(t[x])
            at = np.flatnonzero(np.append(True, v[1:] != v[:-1]))
            most = np.maximum.reduceat(s, at)
            top = np.repeat(most, np.diff(np.append(at, len(v)))) == s
            v, x = v[top], x[top]
            at = np.flatnonzero(np.append(True, v[1:] != v[:-1]))
            to[v[at]], s_to[v[at]] = _least(portable_hash_np(ids[v + lo], ids[x]), x, at), most
        vw = _wide(a["vw"][lo:hi])
        s_own = den * k_own - num * vw * (_wide(t[c[lo:hi]]) - vw)
        leave = (s_own < 0) & ((to == -2) | (s_to < 0))
        to[leave], s_to[leave] = -1, 0
        cand = (to != -2) & wanted(to, s_to, s_own)
        return np.where(cand, to, STAYS), np.where(cand, s_to - s_own, 0), s_own.sum()

    sent = _send(g, c=c, t=t)
    out = over(g, best, ("i4", "i8", "+"), fixed, sent)
    sent.destroy()
    return tuple(out)


def objective(g: Blocks, c: np.ndarray) -> int:
    """den times the objective."""
    t, vw = totals(g, c), g.vw
    return int(g.den * _inside(g, c, "+") - g.num * (int(t @ t) - int(vw @ vw)))


def inside_weight(g: Blocks, b: np.ndarray) -> np.ndarray:
    return _inside(g, b, "i8")


def _inside(g: Blocks, b: np.ndarray, kind: str):
    """Every vertex's weight to its own cluster, or their sum."""

    def inside(a, lo, hi, src, dst, w):
        src, _, w = _within(a, src, dst, w)
        if kind == "+":
            return (w.sum(),)
        out = np.zeros(hi - lo, np.int64)
        np.add.at(out, src - lo, w)
        return (out,)

    sent = _send(g, b=b)
    out = over(g, inside, (kind,), sent)[0]
    sent.destroy()
    return out


def replay(g: Blocks, c, dest, gain, cand, eps, fixed) -> np.ndarray:
    """The candidates that still gain nothing negative after all better-ranked neighbours have moved."""
    num, den = g.num, g.den

    def change(a, lo, hi, src, dst, w):
        v, u, w = _within(a, src, dst, w)
        to = a["to"]
        keep = (to[v] != STAYS) & (to[u] != STAYS)
        u, v, w = u[keep], v[keep], w[keep]
        lead, h = (_wide(a["gain"][u]) - _wide(a["gain"][v])) * eps[1], a["h"]
        keep = (lead >= den * eps[0]) | ((lead > -den * eps[0]) & ((h[u] < h[v]) | ((h[u] == h[v]) & (u < v))))
        u, v, w = u[keep], v[keep], w[keep]
        out, c = np.zeros(hi - lo, np.int64), a["c"]
        np.add.at(out, v - lo, kernel.multiple(c[u], to[u], c[v], to[v]) * (den * w - num * _wide(a["vw"][u]) * _wide(a["vw"][v])))
        return ((to[lo:hi] != STAYS) & (a["gain"][lo:hi] + out >= 0),)

    sent = _send(g, c=c, to=np.where(cand, dest, np.int32(STAYS)), gain=gain)
    out = over(g, change, ("?",), fixed, sent)[0]
    sent.destroy()
    return out


def beside(g: Blocks, marked: np.ndarray) -> np.ndarray:
    """The marked vertices and their neighbours."""

    def near(a, lo, hi, src, dst, w):
        out = np.zeros(hi - lo, bool)
        out[src[a["marked"][dst]] - lo] = True
        return (out,)

    sent = _send(g, marked=marked)
    out = over(g, near, ("?",), sent)[0]
    sent.destroy()
    return out | marked


def _batch_of(g: Blocks, o: Options) -> np.ndarray:
    if o.batching_in_effect() == "degree":
        return degree_class_np(g.deg, o.batches)
    return (portable_hash_np(g.ids, np.zeros(g.n, np.int64), o.seed) % o.batches).astype(int)


def local_move(g: Blocks, c: np.ndarray, o: Options, constraint: np.ndarray | None = None, log: kernel.Log | None = None, level: int = 0, phase: str = "down") -> tuple[np.ndarray, int, int]:
    """(best clustering seen, den times its objective, that of the start) after passes of simultaneous moves."""
    c = c.astype(np.int32, copy=False)
    fixed = _fixed(g, constraint)
    of = _batch_of(g, o) if o.batching_in_effect() else None
    groups = [None] if of is None else [of == k for k in range(of.max() + 1 if g.n else 0)]
    best = best_value = start = active = stuck = last = None
    passed: list = []

    def seen(value):
        nonlocal best, best_value, start
        start = value if start is None else start
        if best_value is None or value > best_value:
            best, best_value = c, value
        if log is not None:
            log.rows += [(*x, value) for x in passed]
        passed.clear()

    for i, phi in enumerate(o.phi):
        if stuck == phi:
            continue
        if phi != last:  # another temperature opens every vertex
            active, last = None, phi
        p, q = phi.numerator, phi.denominator
        moved = np.zeros(g.n, bool)
        for k, group in enumerate(groups):
            dest, gain, value = choose(g, c, totals(g, c), fixed, lambda to, s_to, s_own, p=p, q=q: q * s_to >= (q - p) * s_own)
            if k == 0:
                seen(value)  # the own scores add up to the objective
            cand = dest != STAYS
            for only in (group, active):
                if only is not None:
                    cand &= only
            if o.symmetry == "replay":
                go = replay(g, c, dest, gain, cand, o.eps, fixed) if cand.any() else cand
            elif o.symmetry in ("min_label", "async_min_label") and o.mlh_active(i):
                go = kernel.min_label(g, c, dest, gain, cand & (gain > 0))
            else:
                go = cand & (gain > 0) if o.symmetry != "none" else cand
            del gain, cand
            if not go.any():
                continue
            raw = c.copy()
            raw[go] = np.where(dest[go] == -1, g.n + np.flatnonzero(go), dest[go])
            c = canonical(raw, g.n)
            moved |= go
            del raw, dest, go
        passed.append((level, phase, i, int(moved.sum()), int((c == _each(g.n)).sum())))
        stuck = None if moved.any() else phi
        if o.prune:
            active = beside(g, moved)
    seen(best_value if c is best and best is not None else objective(g, c))
    fixed.destroy()
    return best, best_value, start


def contract(g: Blocks, c: np.ndarray) -> tuple[Blocks, np.ndarray]:
    """The coarse graph and every vertex's coarse vertex (its number there)."""
    lead = c == _each(g.n)
    reps, up = np.flatnonzero(lead), (np.cumsum(lead, dtype=np.int32) - np.int32(1))[c]
    n = len(reps)
    starts = _starts(np.bincount(up, g.deg, n).astype(np.int64))
    sent = _send(g, up=up, starts=starts)

    def coarse(batches):
        up, starts = sent.value["up"], sent.value["starts"]

        def pieces():
            for _, _, src, dst, w in _rows(batches):
                x, y = up[src].astype(np.int64), up[dst].astype(np.int64)
                cut = x != y
                yield x[cut], y[cut], w[cut]

        yield from _gathered(pieces(), starts, n)

    rows, deg = _merged(g.rows.select("lo", "hi", "deg", "dst", "w").mapInArrow(coarse, EDGES), starts, n, sent)
    sent.destroy()
    vw = np.zeros(n, np.int64)
    np.add.at(vw, up, g.vw)
    return Blocks(g.ids[reps], vw, deg, rows, g.num, g.den, None if g.b is None else dense(g.b[reps])), up


def _lone(c: np.ndarray) -> bool:
    return bool((c == _each(len(c))).all())


def _deeper(o: Options, log: kernel.Log, depth: int, more: kernel.Log) -> None:
    log.rows += [(depth + r[0], *r[1:]) if r[0] >= 0 else r for r in more.rows]
    for k, v in more.seconds.items():
        log.seconds[k] = log.seconds.get(k, 0.0) + v


def two_way(g: Blocks, o: Options, start: np.ndarray | None = None, log: kernel.Log | None = None) -> np.ndarray:
    """As in the kernel, which takes over below its limit; g.b is the constraint of the way down."""
    log = log if log is not None else kernel.Log()
    levels, maps, top = [g], [], None
    c = _each(g.n) if start is None else start
    while True:
        here = levels[-1]
        if len(levels) > 1 and here.stored <= o.kernel_limit:
            more = kernel.Log()
            c = kernel.two_way(local(here), o, here.b, None, more)
            _deeper(o, log, len(maps), more)
            top = here
            break
        t = time.perf_counter()
        c = local_move(here, c, o, here.b, log, len(maps))[0]
        log.add("move_down", t)
        if _lone(c) or len(levels) >= o.max_levels:
            break
        t = time.perf_counter()
        coarse, up = contract(here, c)
        log.add("contract", t)
        levels.append(coarse)
        maps.append(up)
        c = _each(coarse.n)
    if o.move_at_top and o.uncoarsen and top is None:
        c = local_move(levels[-1], c, o, None, log, len(maps), "up")[0]
    return _up(levels, maps, c, o, log)


def _up(levels, maps, c, o: Options, log: kernel.Log) -> np.ndarray:
    """The coarse clustering on every finer level, with moves there if wanted; the coarse levels' blocks go."""
    for i in range(len(maps) - 1, -1, -1):
        drop(levels[i + 1].rows)
        c = canonical(c.astype(np.int32, copy=False)[maps[i]], levels[i].n)
        if o.uncoarsen:
            t = time.perf_counter()
            c = local_move(levels[i], c, o, None, log, i, "up")[0]
            log.add("move_up", t)
    return c


def strict_move(g: Blocks, c: np.ndarray, log: kernel.Log | None = None) -> np.ndarray:
    """The best prefix of all vertices that gain by moving, each judged after all before it."""
    fixed = _fixed(g, None)
    dest, gain, _ = choose(g, c, totals(g, c), fixed, lambda to, s_to, s_own: s_to > s_own)
    movers = np.flatnonzero(dest != STAYS)
    movers = movers[np.lexsort((movers, portable_hash_np(g.ids[movers], np.zeros(len(movers), np.int64), 5)))]
    if log is not None:
        log.rows.append((-1, "strict", 0, len(movers), 0, 0))
    if not len(movers):
        fixed.destroy()
        return c
    pos = np.full(g.n, -1)
    pos[movers] = np.arange(len(movers))
    den = g.den

    def near(a, lo, hi, src, dst, w):
        pos, c, to = a["pos"], a["c"], a["to"]
        keep = (pos[dst] >= 0) & (pos[dst] < pos[src])
        v, u, w = src[keep], dst[keep], w[keep]
        out = np.zeros(hi - lo, np.int64)
        np.add.at(out, v - lo, kernel.multiple(c[u], to[u], c[v], to[v]) * den * w)
        return (out,)

    sent = _send(g, pos=pos, c=c, to=dest)
    gains = gain[movers] + over(g, near, ("i8",), fixed, sent)[0][movers]
    sent.destroy()
    fixed.destroy()
    # the weight that has entered or left a mover's two clusters before its turn
    real = np.flatnonzero(dest[movers] >= 0)
    x = np.concatenate([c[movers], dest[movers][real]])
    turn = np.concatenate([np.arange(len(movers)), real])
    weight = np.concatenate([-g.vw[movers], g.vw[movers][real]])
    order = np.lexsort((turn, x))
    run = np.cumsum(weight[order]) - weight[order]
    first = np.append(True, x[order][1:] != x[order][:-1])
    run -= run[np.maximum.accumulate(np.where(first, np.arange(len(x)), 0))]
    drift = np.empty(len(x), np.int64)
    drift[order] = run
    into = np.zeros(len(movers), np.int64)
    into[real] = drift[len(movers) :]
    gains -= g.num * g.vw[movers] * (into - drift[: len(movers)])
    go = movers[: int(np.argmax(np.cumsum(gains))) + 1]
    raw = c.copy()
    raw[go] = np.where(dest[go] == -1, g.n + go, dest[go])
    return canonical(raw, g.n)


def refine(g: Blocks, b: np.ndarray, seed: int, mode: str = "forest") -> np.ndarray:
    """Sub-clusters of the clustering b by a random spanning forest, as in the kernel."""
    n, num, den, greedy = g.n, g.num, g.den, mode == "greedy"
    wb, inside = totals(g, b), inside_weight(g, b)
    ok = den * inside - num * g.vw * (wb[b] - g.vw) >= 0
    fixed = _send(g, vw=g.weights, ids=g.ids, b=b, ok=ok)

    def pick(a, lo, hi, src, dst, w):
        src, dst, w = _within(a, src, dst, w)
        ok, ids = a["ok"], a["ids"]
        s = den * w - num * _wide(a["vw"][src]) * _wide(a["vw"][dst])
        keep = ok[src] & ok[dst] & (s >= 0)
        own = lo + np.flatnonzero(ok[lo:hi])
        v, u = np.concatenate([src[keep], own]), np.concatenate([dst[keep], own])
        out = np.arange(lo, hi)
        if not len(v):
            return (out,)
        order = np.argsort(v, kind="stable")
        v, u = v[order], _wide(u[order])
        at = np.flatnonzero(np.append(True, v[1:] != v[:-1]))
        if greedy:
            s = np.concatenate([s[keep], np.zeros(len(own), np.int64)])[order]
            top = np.repeat(np.maximum.reduceat(s, at), np.diff(np.append(at, len(v)))) == s
            v, u = v[top], u[top]
            at = np.flatnonzero(np.append(True, v[1:] != v[:-1]))
        out[v[at] - lo] = _least(portable_hash_np(ids[v], ids[u], seed), u, at)
        return (out,)

    choice = over(g, pick, ("i4",), fixed)[0]
    fixed.destroy()
    parent, f = kernel.oriented(g, choice, seed)
    root = kernel.roots(parent)
    if mode == "racy":
        return canonical(root, n)
    order = np.lexsort((np.arange(n), f, root))
    pos = np.empty(n, np.int64)
    pos[order] = np.arange(n)

    def before(a, lo, hi, src, dst, w):
        keep = (a["root"][src] == a["root"][dst]) & (a["pos"][dst] < a["pos"][src])
        out = np.zeros(hi - lo, np.int64)
        np.add.at(out, src[keep] - lo, w[keep])
        return (out,)

    sent = _send(g, root=root, pos=pos)
    earlier = over(g, before, ("i8",), sent)[0]
    sent.destroy()
    return kernel.committed(g, b, ok, root, order, wb, inside, earlier)


def refined(g: Blocks, c: np.ndarray | None, o: Options, log: kernel.Log | None = None) -> np.ndarray:
    """As in the kernel, which takes over below its limit."""
    log = log if log is not None else kernel.Log()
    c = _each(g.n) if c is None else c
    levels, maps = [g], []
    while True:
        here = levels[-1]
        if len(levels) > 1 and here.stored <= o.kernel_limit:
            more = kernel.Log()
            c = kernel.refined(local(here), c, o.but(seed=o.seed + 101 * len(maps)), more)
            _deeper(o, log, len(maps), more)
            break
        t = time.perf_counter()
        c, value, before = local_move(here, c, o, None, log, len(maps))
        log.add("move_down", t)
        if value == before:
            c = strict_move(here, c, log)
        if _lone(c) or len(levels) >= o.max_levels:
            break
        t = time.perf_counter()
        for k in range(o.redraw_limit + 1):
            fine = refine(here, c, o.seed + 101 * len(levels) + 7919 * k, o.refine_mode)
            if not _lone(fine):
                break
        log.add("refine", t)
        if _lone(fine):
            break
        t = time.perf_counter()
        coarse, up = contract(here, fine)
        log.add("contract", t)
        below = np.empty(coarse.n, np.int32)
        below[up] = c
        levels.append(coarse)
        maps.append(up)
        c = dense(below)
    return _up(levels, maps, c, o, log)
