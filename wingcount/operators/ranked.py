"""Instances counted by ranks instead of listed.

With the first edge (ux, lx) and its node's second edge b = (ux, ly), an instance is a pair of edges a = (uy, lx), c = (uy, ly) of another node uy in the window. All
pairs of edges of one node are points (earlier time, later time) under their two other nodes, so the orders of a start and its b are counts of points in rectangles, which a
wavelet matrix answers. The work follows from the number of wedges, not from that of instances.

Edges are dealt to cells: a stretch of time at least as wide as tau with what follows within tau, and two classes of nodes, as few as give work to all tasks and a bound to a
cell's edges, as each class is a further copy of the edges. Each cell is one task's numpy arrays, divided there by finer classes; points and starts are taken in parts of some
PART pairs each, and their counts added, so that a crowded cell takes longer but no more memory than its edges and one part.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.functions.order_types import TRANSPOSED, TYPES
from wingcount.operators.joins import bucket

#: Pairs of edges that a task holds at once, the most classes that nodes are dealt to, the most edges that a cell should have, and as how many some are seen for a wide cell.
PART, MOST_CLASSES, MOST_EDGES, WIDE_EDGES = 250_000, 32, 2_000_000, 300_000


class Dominance:
    """Points (p, r) with p < r in groups; counts of those in a rectangle for many queries at once. Times are ranks below `span`."""

    def __init__(self, group: np.ndarray, p: np.ndarray, r: np.ndarray, span: int):
        self.span = span
        self.groups, g = np.unique(group, return_inverse=True)
        by = np.argsort(g * span + p, kind="stable")
        g, r = g[by], r[by]
        self.first = g * span + p[by]
        self.second = np.sort(g * span + r)
        sizes = np.bincount(g, minlength=len(self.groups))
        self.start = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
        local = np.empty(len(r), np.int32)
        local[np.argsort(g * span + r, kind="stable")] = np.arange(len(r), dtype=np.int64) - self.start[g]
        self.bits = int(sizes.max()).bit_length() if len(sizes) else 0
        self.zeros: list[np.ndarray] = []
        for bit in range(self.bits - 1, -1, -1):
            one = (local >> bit) & 1 == 1
            at = np.zeros(len(local) + 1, np.int32)
            np.cumsum(~one, out=at[1:])
            self.zeros.append(at)
            local = np.concatenate([local[~one], local[one]])

    def at(self, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of each asked group, and whether there is one."""
        if not len(self.groups):
            return np.zeros(len(group), np.int64), np.zeros(len(group), bool)
        k = np.minimum(np.searchsorted(self.groups, group), len(self.groups) - 1)
        return k, self.groups[k] == group

    def _less(self, s: np.ndarray, e: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """How many of the points at [s, e) have a second time below the rank (within their group)."""
        out = np.zeros(len(s), np.int64)
        for at, bit in zip(self.zeros, range(self.bits - 1, -1, -1), strict=True):
            s0, e0 = at[s], at[e]
            one = (rank >> bit) & 1 == 1
            out += np.where(one, e0 - s0, 0)
            s, e = np.where(one, at[-1] + s - s0, s0), np.where(one, at[-1] + e - e0, e0)
        return out

    def count(self, g: np.ndarray, low: np.ndarray, mid: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Points of group number g with low < p < mid < r <= high; with low < p and r < mid; with mid < p and r <= high."""
        base, offset = g * self.span, self.start[g]
        rank = lambda x, k: (np.searchsorted(self.second, base[k] + x[k], "right") - offset[k]).astype(np.int32)
        place = lambda x: np.searchsorted(self.first, base + x, "right").astype(np.int32)
        across, before, after = (np.zeros(len(g), np.int64) for _ in range(3))
        s, e, s_after, e_after = place(low), place(mid - 1), place(mid), place(high)
        if len(k := np.flatnonzero(e > s)):
            below, upto, most = rank(mid - 1, k), rank(mid, k), rank(high, k)
            before[k] = self._less(s[k], e[k], below)
            tied = np.flatnonzero(upto != below)
            across[k] = self._less(s[k], e[k], most) - before[k]
            across[k[tied]] += before[k[tied]] - self._less(s[k[tied]], e[k[tied]], upto[tied])
        if len(k := np.flatnonzero(e_after > s_after)):
            after[k] = self._less(s_after[k], e_after[k], rank(high, k))
        return across, before, after


def _pairs(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(k, i) for all i in [begin[k], end[k])."""
    n = np.maximum(end - begin, 0)
    k = np.repeat(np.arange(len(n)), n)
    return k, np.arange(len(k)) - np.repeat(np.cumsum(n) - n, n) + begin[k]


def _parts(n: np.ndarray) -> list[tuple[int, int]]:
    """Stretches of rows with some PART pairs each; a row is not divided."""
    upto = np.cumsum(n)
    cuts = np.unique(np.searchsorted(upto, np.arange(PART, int(upto[-1]) + PART, PART), "left") + 1) if len(n) else []
    cuts = [0, *(int(x) for x in cuts if x < len(n)), len(n)]
    return [(a, b) for a, b in zip(cuts, cuts[1:]) if b > a]


def count_cell(edges: tuple[np.ndarray, ...], starts: tuple[np.ndarray, ...], tau: int, pair: tuple[int, int] = (0, 0), kinds: tuple[int, ...] = TYPES) -> np.ndarray:
    """c1..c6 (a column each) of the starts (u, l, t, class of l) by the edges that may lie in their windows: instances whose lx and ly are of the two classes of `pair`.
    Types that are not among `kinds` may stay 0."""
    u, l, t, h = edges
    su, sl, st, sh = starts
    out = np.zeros((len(su), 6), np.int64)
    if not len(u) or not len(su):
        return out
    users, u = np.unique(np.concatenate([u, su]), return_inverse=True)
    nodes, l = np.unique(np.concatenate([l, sl]), return_inverse=True)
    times, t_ = np.unique(np.concatenate([t, st]), return_inverse=True)
    (u, su), (l, sl), (t_, st_), m, span = np.split(u, [len(t)]), np.split(l, [len(t)]), np.split(t_, [len(t)]), len(nodes), len(times) + 1
    last = np.searchsorted(times, times + tau, "right") - 1  # the rank of the latest time in the window after each time
    by = np.lexsort((t_, u))
    u, l, t_, h = u[by], l[by], t_[by], h[by]
    key = u * span + t_
    apart = lambda a, b: ((a == pair[0]) & (b == pair[1])) | ((a == pair[1]) & (b == pair[0]))
    order = np.lexsort((st_, su))
    su, sl, st_, sh = su[order], sl[order], st_[order], sh[order]
    from_, to = np.searchsorted(key, key, "right"), np.searchsorted(key, u * span + last[t_], "right")
    s_from, s_to = np.searchsorted(key, su * span + st_, "right"), np.searchsorted(key, su * span + last[st_], "right")
    found = np.zeros((len(su), 6), np.int64)
    for lo, hi in _parts(np.maximum(to - from_, 0)):
        k, i = _pairs(from_[lo:hi], to[lo:hi])
        k += lo
        keep = (l[k] != l[i]) & apart(h[k], h[i])
        k, i = k[keep], i[keep]
        if not len(k):
            continue
        under = l[k] * m + l[i]
        all_ = Dominance(under, t_[k], t_[i], span)
        own = Dominance(u[k] * len(all_.groups) + all_.at(under)[0], t_[k], t_[i], span)  # a start's own node is no uy
        for a, b in _parts(np.maximum(s_to - s_from, 0)):
            k, i = _pairs(s_from[a:b], s_to[a:b])
            k += a
            keep = (sl[k] != l[i]) & apart(sh[k], h[i])
            k, i = k[keep], i[keep]
            for first, second, named in ((sl[k], l[i], (1, 2, 3)), (l[i], sl[k], (6, 4, 5))):
                if not set(named) & set(kinds):
                    continue
                g, held = all_.at(first * m + second)
                at = np.flatnonzero(held)
                g = g[at]
                own_g, mine = own.at(su[k[at]] * len(all_.groups) + g)
                near = np.argsort(g, kind="stable")  # neighbours ask for neighbours
                at, g, own_g, mine = at[near], g[near], own_g[near], mine[near]
                low, mid, high = st_[k[at]], t_[i[at]], last[st_[k[at]]]
                n = np.array(all_.count(g, low, mid, high))
                mine = np.flatnonzero(mine)
                n[:, mine] -= np.array(own.count(own_g[mine], low[mine], mid[mine], high[mine]))
                rows = k[at]
                for x, c in zip(n, named, strict=True):
                    some = np.flatnonzero(x)
                    np.add.at(found[:, c - 1], rows[some], x[some])
    out[order] = found
    return out


def classes_for(wedges: float, edges: float, cells: int, tasks: int) -> int:
    """Classes of nodes that edges are dealt by, so that there is work for all tasks and a cell has MOST_EDGES edges or so."""
    k = 1
    while k < 4 and cells * k * (k + 1) / 2 < tasks and wedges > PART:
        k += 1
    while k < MOST_CLASSES and 2 * edges / max(1, cells) * min(1, 2 / k) > MOST_EDGES:
        k += 1
    return k


def finer(wedges: float, cells: int, classes: int) -> int:
    """Into how many a task divides each class, so that a pair of them has some PART wedges."""
    q = 1
    while q * classes < 2 * MOST_CLASSES and wedges / max(1, cells) / (q * classes * (q * classes + 1) / 2) > PART:
        q += 1
    return q


def ranked(
    edges: DataFrame, starts: DataFrame, taus: int | list[int], center: str = "auto", width: int | None = None, totals: bool = False, kinds: tuple[int, ...] = TYPES,
    label: str = "eid", weighed: bool = False, runs: tuple[tuple[int, ...], ...] | None = None,
) -> DataFrame:
    """(tau, eid, c1..c6) of the starts that begin an instance, or with `totals` the same with eid -1 in parts to be added, under 'strict'. `center` is the layer whose nodes'
    pairs of edges are the points ('auto': the one with fewer of them). `label` is the starts' column that counts are added by in place of their ids. With `weighed`, starts
    have copies and weight, and (tau, weight, c1..c6) are sums of copies * count in parts to be added. `runs`: groups of types that are each counted on their own."""
    from wingcount.plans.planner import window_work

    taus = [taus] if isinstance(taus, int) else sorted(taus)
    spark, most = edges.sparkSession, max(1, max(taus))
    if width is not None and max(1, width) < max(taus):
        raise ValueError("a bucket is at least as wide as tau")
    lower, upper, _ = window_work(edges, most)
    center = ("lower" if lower <= upper else "upper") if center == "auto" else center
    u, l = ("u", "l") if center == "upper" else ("l", "u")
    wedges, tasks = lower if center == "lower" else upper, 2 * spark.sparkContext.defaultParallelism
    low, high, m = edges.agg(F.min("t"), F.max("t"), F.count(F.lit(1))).first()
    if width is None:  # a wide cell has few edges twice
        wanted = max(2 * tasks, m // WIDE_EDGES, int(wedges // PART)) + 1
        width = most if low is None else max(most, (high - low + 1) // wanted)
    width = max(1, width)
    cells = 1 if low is None else high // width - low // width + 1
    classes = classes_for(wedges, m, cells, tasks)
    inner = finer(wedges, cells, classes)
    # pairs of classes are numbered; a node's edges go to all pairs that its class is in
    numbers = {(i, j): n for n, (i, j) in enumerate((i, j) for i in range(classes) for j in range(i, classes))}
    pairs = list(numbers)
    holds = [[n for (i, j), n in numbers.items() if k in (i, j)] for k in range(classes)]

    own, of = bucket(F.col("t"), width), F.pmod(F.xxhash64(l), F.lit(classes * inner)).cast("long")
    # role 0: an edge; 1: a start; 2: both. One number holds class and role
    row = lambda role: (F.col(u).alias("u"), F.col(l).alias("l"), "t", (of * 3 + F.lit(role)).alias("h"))
    named = [] if totals else ["copies", "weight"] if weighed else ["eid"]
    its = [F.col(label).alias("eid")] if named == ["eid"] else [F.col(c) for c in named]
    kind = {"eid": "long", "copies": "long", "weight": "double"}
    near = lambda b, role, own_row=False: edges.select(*(its if own_row else [F.lit(None).cast(kind[c]).alias(c) for c in named]), *row(role), b.alias("b"))
    if starts is edges and not weighed:
        both = near(own, 2, True)
    else:
        both = near(own, 0).unionByName(starts.select(*its, *row(1), own.alias("b")))
    both = both.unionByName(near(own - 1, 0).where(F.col("t") - (F.col("b") + 1) * F.lit(width) < F.lit(most)))  # within tau of the stretch before
    if classes == 1:
        both = both.withColumnRenamed("b", "cell")
    else:
        pair = F.explode(F.element_at(F.array(*(F.array(*map(F.lit, x)) for x in holds)), F.floor(F.col("h") / F.lit(3 * inner)).cast("int") + 1))
        both = both.withColumn("k", pair).withColumn("cell", F.col("b") * F.lit(len(pairs)) + F.col("k")).drop("b", "k")
    kept = [TRANSPOSED[k] - 1 if center == "lower" else k - 1 for k in TYPES]
    sought = [tuple(kept[k - 1] + 1 for k in run) for run in runs or (kinds,)]
    names = [f"c{k}" for k in TYPES]
    added_by = label != "eid"

    def count(table: pa.Table) -> pa.Table:
        i, j = pairs[int(table.column("cell")[0].as_py()) % len(pairs)]
        h = table.column("h").to_numpy()
        role, h = (h % 3).astype(np.int8), (h // 3).astype(np.int16)
        col = {c: np.unique(table.column(c).to_numpy(), return_inverse=True)[1].astype(np.int32) for c in ("u", "l")} | {"t": table.column("t").to_numpy(), "h": h}
        e, s = (tuple(col[c][x] for c in ("u", "l", "t", "h")) for x in (role != 1, role != 0))
        mine = {c: table.column(c).filter(pa.array(role != 0)).to_numpy() for c in named}
        del table, col
        finest = [(a, b) for a in range(i * inner, i * inner + inner) for b in range(j * inner, j * inner + inner) if i != j or a <= b]
        parts = []
        for tau in taus:
            n = np.zeros((len(s[0]), 6), np.int64)
            for a, b in finest:
                x, y = ((z[3] == a) | (z[3] == b) for z in (e, s))
                at = np.flatnonzero(y)
                for run in sought:
                    of = [k - 1 for k in run]  # other types may be counted along
                    n[np.ix_(at, of)] += count_cell(tuple(z[x] for z in e), tuple(z[at] for z in s), tau, (a, b), run)[:, of]
            n = n[:, kept]
            some = np.flatnonzero(n.any(axis=1))
            n, keys = n[some], {c: v[some] for c, v in mine.items()}
            if totals:
                n, keys = n.sum(axis=0, keepdims=True), {"eid": np.full(1, -1)}
            elif weighed or added_by:
                by = "weight" if weighed else "eid"
                n = n * keys["copies"][:, None] if weighed else n
                keys, at = np.unique(keys[by], return_inverse=True)
                out = np.zeros((len(keys), 6), np.int64)
                np.add.at(out, at, n)
                n, keys = out, {by: keys}
            parts.append(pa.table({"tau": pa.array(np.full(len(n), tau))} | {c: pa.array(v) for c, v in keys.items()} | {c: pa.array(np.ascontiguousarray(n[:, k])) for k, c in enumerate(names)}))
        out = pa.concat_tables(parts).combine_chunks()
        pa.default_memory_pool().release_unused()
        return out

    key = "weight double" if weighed else "eid long"
    got = both.groupBy("cell").applyInArrow(count, f"tau long, {key}, " + ", ".join(f"{c} long" for c in names))
    if totals or weighed or (classes == 1 and not added_by):
        return got
    return got.groupBy("tau", "eid").agg(*(F.sum(c).alias(c) for c in names))
