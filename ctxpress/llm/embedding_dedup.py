"""Near-duplicate vectors by dual traversal of cover trees: all pairs at or over a cosine, and no other.

On the unit sphere a cosine is a distance, so a threshold is a radius. Where a label has many vectors, a bounded sample of
them fits a tree of hyperplanes, and every vector is dealt to the cell that it lies in; one that lies below a plane by no
more than the radius also visits the other side, where its partners may be. In a cell, a tree of nested covers with halving
radii is walked against itself: a pair of nodes is left out when its centres are farther apart than both covering radii and
the threshold allow, taken in whole when they are that close, and split otherwise, down to leaves of some dozens of vectors,
which one matrix product decides.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.llm.common import cut_lineage
from ctxpress.llm.graph import connected_components
from ctxpress.llm.simhash import unite

COSINE, SLACK, LEAF = 0.98, 1e-6, 128


def distance(dot: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, 2.0 - 2.0 * dot))


class CoverTree:
    """Nodes over unit vectors; every child covers its members within half of its parent's radius or less. Up to ``leaf`` members are not split."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        self.x, order = x, np.arange(len(x))
        root = distance(x @ x[0])
        self.center, self.radius, self.first, self.stop, self.kids = [0], [float(root.max())], [0], [len(x)], [None]
        todo = [(0, root)]
        while todo:
            node, dist = todo.pop()
            rho, lo, hi = self.radius[node], self.first[node], self.stop[node]
            if rho <= SLACK or hi - lo <= leaf:
                continue
            members = order[lo:hi].copy()
            centers, owner, gap = self._cover(members, int(np.argmin(dist)), rho / 2)  # the centre of a node stays one below it
            by = np.argsort(owner, kind="stable")
            order[lo:hi] = members[by]
            at = np.searchsorted(owner[by], np.arange(len(centers)))
            stop, wide = np.r_[at[1:], len(by)], np.maximum.reduceat(gap[by], at)
            self.kids[node] = len(self.center) + np.arange(len(centers))
            todo += [(len(self.center) + k, gap[by[at[k] : stop[k]]]) for k in np.flatnonzero(stop - at > leaf).tolist()]
            self.center += members[centers].tolist()
            self.radius += wide.tolist()
            self.first += (lo + at).tolist()
            self.stop += (lo + stop).tolist()
            self.kids += [None] * len(centers)
        self.order = order
        self.center, self.radius, self.first, self.stop = (np.array(v) for v in (self.center, self.radius, self.first, self.stop))

    def _cover(self, members: np.ndarray, start: int, rho: float, some: int = 256) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Centres among ``members``, each member's centre and its distance; no two centres are within ``rho``."""
        x = self.x[members]
        owner, gap, centers = np.full(len(x), -1), np.zeros(len(x)), []
        left = np.r_[start, np.delete(np.arange(len(x)), start)]
        while len(left):
            block = left[:some]
            near = distance(x[block] @ x[block].T) <= rho
            covered, new = np.zeros(len(block), bool), []
            for i in range(len(block)):
                if not covered[i]:
                    new.append(i)
                    covered |= near[i]
            new = block[new]
            for part in np.array_split(left, -(-len(left) * len(new) // 2_000_000)):
                d = distance(x[part] @ x[new].T)
                held = d <= rho
                some_one, which = held.any(1), held.argmax(1)
                owner[part[some_one]] = len(centers) + which[some_one]
                gap[part[some_one]] = d[some_one, which[some_one]]
            owner[new], gap[new] = len(centers) + np.arange(len(new)), 0.0
            centers += new.tolist()
            left = left[owner[left] < 0]
        return np.array(centers), owner, gap


class _Links:
    """Walks a cover tree against itself and gathers links. Guests do not link to guests."""

    def __init__(self, x: np.ndarray, weight: np.ndarray, home: np.ndarray, cosine: float, leaf: int):
        self.x, self.weight, self.home, self.cosine, self.tree = x, weight, home, cosine, CoverTree(x, leaf)
        self.at_home, self.reach = np.where(home, weight, 0), float(np.sqrt(2.0 - 2.0 * cosine))
        self.parent, self.links, self.edges, self.held = np.arange(len(x)), np.zeros(len(x), np.int64), [], 0

    def members(self, node: int) -> np.ndarray:
        return self.tree.order[self.tree.first[node] : self.tree.stop[node]]

    def tie(self, i: np.ndarray, j: np.ndarray) -> None:
        self.edges.append((i, j))
        self.held += len(i)
        if self.held > 1_000_000:
            self.settle()

    def settle(self) -> None:
        if self.edges:
            unite(self.parent, *(np.concatenate(v) for v in zip(*self.edges)))
        self.edges, self.held = [], 0

    def points(self, i: np.ndarray, j: np.ndarray) -> None:
        """Links i[k] and j[k], all of them distinct pairs."""
        ok = self.home[i] | self.home[j]
        i, j = i[ok], j[ok]
        np.add.at(self.links, i, np.where(self.home[i], self.weight[j], self.at_home[j]))
        np.add.at(self.links, j, np.where(self.home[j], self.weight[i], self.at_home[i]))
        self.tie(i, j)

    def product(self, ma: np.ndarray, mb: np.ndarray | None = None) -> None:
        """Decides all pairs of two groups, or of one, by their cosines."""
        for lo in range(0, len(ma), 2048):
            part, other = ma[lo : lo + 2048], ma[lo:] if mb is None else mb
            hit = self.x[part] @ self.x[other].T >= self.cosine
            i, j = np.nonzero(np.triu(hit, 1) if mb is None else hit)
            if len(i):
                self.points(part[i], other[j])

    def leaves(self, a: int, others: list[int]) -> None:
        """Decides the pairs of one leaf with ``others``, among which it may be itself."""
        mine, rest = self.members(a), [self.members(b) for b in others if b != a]
        if a in others:
            self.product(mine)
        if rest:
            self.product(mine, np.concatenate(rest))

    def whole(self, a: int, b: int) -> None:
        """Links all pairs of two nodes without naming them."""
        ma, mb, home = self.members(a), self.members(b), self.home
        if not (home[ma].any() or home[mb].any()):
            return
        for one, other in ((ma, mb), (mb, ma)) if a != b else ((ma, ma),):
            self.links[one] += np.where(home[one], self.weight[other].sum(), self.at_home[other].sum())
        if a == b:
            self.links[ma] -= np.where(home[ma], self.weight[ma], 0)
            self.tie(ma, np.full(len(ma), ma[home[ma]][0]))
            return
        for one, other in ((ma, mb), (mb, ma)):  # chains need a member at home on one side
            h = one[home[one]]
            if len(h):
                self.tie(other, np.full(len(other), h[0]))
                self.tie(h, np.full(len(h), other[0]))

    def walk(self) -> None:
        t = self.tree
        size, leaf = t.stop - t.first, np.array([k is None for k in t.kids])
        todo = [(0, 0)]
        while todo:
            a, b = todo.pop()
            if leaf[a] and leaf[b]:
                self.product(self.members(a), None if a == b else self.members(b))
                continue
            ka = np.array([a]) if leaf[a] else t.kids[a]
            kb = np.array([b]) if leaf[b] else t.kids[b]
            step = max(1, 2_000_000 // len(kb))
            for lo in range(0, len(ka), step):
                kp = ka[lo : lo + step]
                kq = kb[lo:] if a == b else kb  # of a node with itself, each pair of children once
                dot = self.x[t.center[kp]] @ self.x[t.center[kq]].T
                both = t.radius[kp][:, None] + t.radius[kq][None, :]
                d = distance(dot)
                near = d <= both + self.reach + SLACK
                if a == b:
                    near &= np.arange(len(kp))[:, None] <= np.arange(len(kq))[None, :]
                single = (size[kp] == 1)[:, None] & (size[kq] == 1)[None, :]
                i, j = np.nonzero(near & single & (dot >= self.cosine))
                i, j = t.center[kp[i]], t.center[kq[j]]
                self.points(i[i != j], j[i != j])
                i, j = np.nonzero(near & ~single)
                inside = d[i, j] + both[i, j] <= self.reach - SLACK
                i, j = kp[i], kq[j]
                for p, q in zip(i[inside].tolist(), j[inside].tolist()):
                    self.whole(p, q)
                i, j = i[~inside], j[~inside]
                small = leaf[i] & leaf[j]
                todo += zip(i[~small].tolist(), j[~small].tolist())
                i, j = i[small], j[small]
                at = np.flatnonzero(np.r_[True, i[1:] != i[:-1]]) if len(i) else i
                for s, e in zip(at.tolist(), [*at[1:].tolist(), len(i)]):
                    self.leaves(int(i[s]), j[s:e].tolist())
        self.settle()


def links_within(x: np.ndarray, weight: np.ndarray, home: np.ndarray, cosine: float, leaf: int = LEAF) -> tuple[np.ndarray, np.ndarray]:
    """For each unit vector the weight of its partners, and the least index reachable. Guests do not link to guests."""
    found = _Links(x, weight, home, cosine, leaf)
    found.walk()
    return found.links, found.parent


class Planes:
    """A tree of hyperplanes over a sample; leaves are cells."""

    def __init__(self, sample: np.ndarray, per_leaf: int, reach: float):
        self.normal, self.offset, self.kids, self.cells, self.reach = [], [], [], 0, reach
        todo = [(np.arange(len(sample)), None, 0)]
        while todo:
            at, above, side = todo.pop()
            plane = self._plane(sample[at], reach) if len(at) > per_leaf else None
            if plane is None:
                name, self.cells = -1 - self.cells, self.cells + 1
            else:
                name = len(self.normal)
                self.normal.append(plane[0])
                self.offset.append(plane[1])
                self.kids.append([0, 0])
                low = sample[at] @ plane[0] < plane[1]
                todo += [(at[low], name, 0), (at[~low], name, 1)]
            if above is not None:
                self.kids[above][side] = name

    @staticmethod
    def _plane(x: np.ndarray, reach: float) -> tuple[np.ndarray, float] | None:
        """Across the direction of most spread, at the median; none where most would visit the other side."""
        c = x - x.mean(0)
        u = c[np.argmax((c * c).sum(1))]
        for _ in range(12):
            u = c.T @ (c @ u)
            size = np.sqrt(u @ u)
            if size == 0:
                return None
            u = u / size
        at = x @ u
        t = float(np.median(at))
        low = at < t
        return (u, t) if low.any() and (~low).any() and (low & (at >= t - reach)).mean() < 0.45 else None

    def deal(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, cell, home): each row once at home, and once in each other cell where a partner at home may be."""
        out, reach = [], self.reach + SLACK
        todo = [(0 if self.normal else -1, np.arange(len(x)), np.zeros(0, int))]
        while todo:
            node, home, guest = todo.pop()
            if not len(home) and not len(guest):
                continue
            if node < 0:
                out.append((np.r_[home, guest], np.full(len(home) + len(guest), -1 - node), np.arange(len(home) + len(guest)) < len(home)))
                continue
            h, g = x[home] @ self.normal[node] - self.offset[node], x[guest] @ self.normal[node] - self.offset[node]
            todo.append((self.kids[node][0], home[h < 0], guest[g <= reach]))
            todo.append((self.kids[node][1], home[h >= 0], np.r_[home[(h < 0) & (h >= -reach)], guest[g >= -reach]]))
        return tuple(np.concatenate(v) for v in zip(*out)) if out else (np.zeros(0, int), np.zeros(0, int), np.zeros(0, bool))


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    arr = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = arr.flatten().cast(pa.float64()).to_numpy(zero_copy_only=False)
    x = flat.reshape(len(arr), -1)
    return x / np.sqrt((x * x).sum(1))[:, None]


def _cells(planes: dict):
    """Batches (kind, vec, rep, n) to a row for each cell that a vector is in."""

    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            code = b.column(0).dictionary_encode()
            names, code = code.dictionary.to_pylist(), code.indices.to_numpy()
            row, cell, home = [np.flatnonzero(~np.isin(code, [i for i, k in enumerate(names) if k in planes]))], [], []
            cell.append(np.zeros(len(row[0]), int))
            home.append(np.ones(len(row[0]), bool))
            for i, k in enumerate(names):
                if k in planes:
                    at = np.flatnonzero(code == i)
                    r, c, h = planes[k].deal(_matrix(b.column(1).take(pa.array(at))))
                    row.append(at[r])
                    cell.append(c)
                    home.append(h)
            row = pa.array(np.concatenate(row))
            vec, rep, n = (b.column(i).take(row) for i in (1, 2, 3))
            yield pa.RecordBatch.from_arrays([b.column(0).take(row), pa.array(np.concatenate(cell).astype(np.int32)), pa.array(np.concatenate(home)), vec, rep, n], names=["kind", "cell", "home", "vec", "rep", "n"])

    return f


def fit_planes(unique: DataFrame, reach: float, per_cell: int, most_sample: int, share: int = 16) -> dict:
    """Planes for each label with more than ``per_cell`` vectors, by its part of a hashed sample of at most about ``most_sample``."""
    step = max(1, per_cell // share, -(-unique.count() // most_sample))
    some: dict = {}
    for r in unique.where(F.pmod(F.xxhash64("rep"), F.lit(step)) == 0).orderBy("rep").select("kind", "vec").collect():
        some.setdefault(r["kind"], []).append(r["vec"])
    per_leaf = max(2, per_cell // step)
    some = {k: np.array(v) for k, v in some.items() if len(v) > per_leaf}
    planes = {k: Planes(x / np.sqrt((x * x).sum(1))[:, None], per_leaf, reach) for k, x in some.items()}
    return {k: p for k, p in planes.items() if p.cells > 1}


def _cell_links(cosine: float):
    def f(table: pa.Table) -> pa.Table:
        rep = table.column("rep").to_numpy()
        order = np.argsort(rep, kind="stable")
        x, n, home = _matrix(table.column("vec"))[order], table.column("n").to_numpy()[order], table.column("home").to_numpy()[order]
        links, parent = links_within(x, n, home, cosine)
        some = np.flatnonzero(links > 0)
        return pa.table({"rep": rep[order][some], "links": links[some], "root": rep[order][parent[some]]})

    return f


def dealt_vectors(unique: DataFrame, cosine: float, per_cell: int, most_sample: int) -> DataFrame:
    """(kind, cell, home, vec, rep, n): rows of ``unique`` (kind, vec, rep, n) at home, and as guests where partners may be."""
    planes = fit_planes(unique, float(np.sqrt(2.0 - 2.0 * cosine)), per_cell, most_sample)
    return unique.select("kind", "vec", "rep", "n").mapInArrow(_cells(planes), "kind string, cell int, home boolean, vec array<double>, rep long, n long")


def cosine_components(vectors: DataFrame, cosine: float = COSINE, per_cell: int = 8192, most_sample: int = 80_000) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of ``vectors`` (vec_id, embedding, label).

    Vectors link when their labels and numbers of components are equal and their cosine is at least ``cosine``. A null
    vec_id, label or vector, a zero vector, and one with a null or non-finite component link with nothing. Equal vectors are
    one vector with a count. Labels with more than about ``per_cell`` distinct vectors are cut into cells by planes; the
    planes are fitted on at most about ``most_sample`` vectors, beyond 40 million vectors cells get larger instead.
    """
    whole = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    fit = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & F.col("embedding").isNotNull() & whole & F.exists("embedding", lambda v: v != 0)
    rows = vectors.select("vec_id", F.concat_ws(":", F.col("label").cast("string"), F.size("embedding").cast("string")).alias("kind"), F.col("embedding").cast("array<double>").alias("vec"), F.coalesce(fit, F.lit(False)).alias("fit"))
    unique = cut_lineage(rows.where("fit").groupBy("kind", "vec").agg(F.min("vec_id").cast("long").alias("rep"), F.count("*").alias("n")))
    dealt = dealt_vectors(unique, cosine, per_cell, most_sample)
    found = cut_lineage(dealt.groupBy("kind", "cell").applyInArrow(_cell_links(cosine), "rep long, links long, root long"))
    roots = connected_components(found, "rep", "root")
    totals = found.groupBy("rep").agg(F.sum("links").alias("links"))
    named = unique.join(totals, "rep", "left").join(roots, unique["rep"] == roots["node"], "left")
    named = named.select("kind", "vec", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("root", "rep").alias("component_id"))
    linked = rows.where("fit").join(named, ["kind", "vec"]).select("vec_id", "n_links", "component_id")
    alone = rows.where(~F.col("fit")).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"))
    return linked.unionAll(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op10_embedding_near_dedup(spark, sf_dir: str) -> DataFrame:
    """All rows of ``embeddings`` with links at a cosine of 0.98; nulls, ties and empty tables as in ``cosine_components``."""
    return cosine_components(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
