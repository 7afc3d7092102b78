"""Exact embedding near-duplicates: cover trees and dual traversal.

Vectors are compared by cosine in double precision; on unit vectors the threshold is a chord length. Equal vectors are one class with
a count. Classes of one length go to the nearest of some pivots (the top net, about one pivot a block of data, from a bounded sample);
each pivot's cell is split by hash into blocks of a bounded number of rows, and pairs of cells further apart than their radii and
the threshold allow are never formed. A cover tree of each block is built once and travels with it: nested nets whose radii halve
from level to level, every row in the subtree of the first net point that covers it, every node with the true radius of its rows. Tasks
get pairs of groups of blocks and walk both trees of every pair of blocks at once. Children of two nodes are compared in one matrix
product; pairs too far apart for their radii are dropped, pairs wholly within the threshold are counted as they are, the others are
entered, and single rows are decided there (unordered pairs of one tree once). Where nets spare nothing, as small nodes are too wide or
rows lie alone, rows are compared by their heads first, a few coordinates whose product bounds the cosine from above, and in full only if
that bound reaches the threshold. Tasks return each class's number of links and a spanning forest, never its pairs.

Exact search over data without clusters compares all blocks: the work is quadratic there, the memory is not.

Vectors that are null, empty, zero or hold null or non-finite components link with nothing, and so do vectors of different lengths (any
number of lengths is handled in the same pass). Vectors are scaled before their norm is taken, so very large and very small ones link
like others. Rows with a repeated vec_id are separate vectors; null ids are never a component's name unless all of it are null. An empty
table gives an empty result. Columns other than ``vec_id`` and ``embedding`` are not read and may have any name.
"""

from __future__ import annotations

import pickle
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import graph
from ._util import drop, keep, min_labels, ship, width

THRESHOLD, PIVOTS, SAMPLE, BLOCK, LEAF = 0.95, 1024, 16_384, 8192, 32
#: Room for rounding: of lengths in bounds, of cosines that are looked at again from the vectors as given, and of heads' products.
SLACK, UNSURE, ROUGH = 1e-7, 1e-9, 1e-5
#: Bytes of the blocks of one side that a task compares with those of another.
TILE = 32 << 20
#: Coordinates of a head besides an eighth of the vector's; nodes of so many rows or fewer are compared row by row.
HEAD, FEW = 8, 4


def chord(cosine: float) -> float:
    return float(np.sqrt(max(0.0, 2 - 2 * cosine)))


def unit(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows scaled by their largest component (so that squares neither overflow nor vanish), and unit rows."""
    scaled = x / np.abs(x).max(1, keepdims=True)
    return scaled, scaled / np.linalg.norm(scaled, axis=1, keepdims=True)


@lru_cache(maxsize=64)
def axes(dim: int) -> np.ndarray:
    """Some orthonormal directions, the same for every block of a length; none where they would not spare work."""
    k = HEAD + dim // 8 - 1
    return np.linalg.qr(np.random.default_rng(dim).normal(size=(dim, k)))[0] if 2 * k <= dim else np.zeros((dim, 0))


def heads(u: np.ndarray) -> np.ndarray:
    """Unit rows in few single-precision coordinates: those along ``axes`` and the length of what is left. Products of heads are never
    below the cosine (but for rounding, see ``ROUGH``), as what is left of two rows has at most the product of its lengths."""
    h = u @ axes(u.shape[1])
    return np.c_[h, np.sqrt(np.maximum(0.0, 1 - np.einsum("ij,ij->i", h, h)))].astype(np.float32) if h.shape[1] else np.zeros((len(u), 0), np.float32)


class CoverTree:
    """Nested nets over unit rows ``x`` as flat arrays by node: centre row, covering radius, number of rows, children. Below ``leaf``
    rows a node's children are its rows; ``rows_of`` lists a node's rows; ``depth`` is the number of levels."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        self.x, self.narrow, self.leaf, self.depth = x, x.astype(np.float32), leaf, 0
        self._made: list[tuple[int, float, int, int]] = []
        self._kids: list[list[int]] = []
        self._order: list[int] = []
        if len(x):
            self._node(0, np.arange(len(x)), 2.0, 1)
        made = np.array(self._made, float).reshape(-1, 4)
        self.centre, self.size, self._first = (made[:, i].astype(np.int64) for i in (0, 2, 3))
        self.radius = made[:, 1]
        self.kid_count = np.fromiter(map(len, self._kids), np.int64, len(self._kids))
        self.kid_first = np.cumsum(self.kid_count) - self.kid_count
        self.kids = np.array([k for some in self._kids for k in some], np.int64)
        self._order = np.array(self._order, np.int64)

    def pack(self) -> tuple:
        """The tree without its rows' coordinates."""
        return self.leaf, self.depth, self.radius, *(a.astype(np.int32) for a in (self.centre, self.size, self._first, self.kid_count, self.kids, self._order))

    @classmethod
    def unpack(cls, packed: tuple) -> CoverTree:
        tree = cls.__new__(cls)
        tree.leaf, tree.depth, tree.radius, *rest = packed
        tree.centre, tree.size, tree._first, tree.kid_count, tree.kids, tree._order = (a.astype(np.int64) for a in rest)
        tree.kid_first = np.cumsum(tree.kid_count) - tree.kid_count
        return tree

    def rows_of(self, node: int) -> np.ndarray:
        return self._order[self._first[node] : self._first[node] + self.size[node]]

    def parts(self, node: int) -> np.ndarray:
        """Children of a node; a single row is its own."""
        n = self.kid_count[node]
        return self.kids[self.kid_first[node] : self.kid_first[node] + n] if n else np.array([node])

    def opened(self, node: int, wide: float) -> np.ndarray:
        """Children of a node, with the rows of those that hold few, or at most ``leaf`` within more than ``wide``, in their place."""
        a = self.parts(node)
        size = self.size[a]
        apart = (size > 1) & (size <= self.leaf) & ((size <= FEW) | (self.radius[a] > wide))
        n = self.kid_count[a[apart]]  # a node of at most ``leaf`` rows has them as its children
        return np.r_[a[~apart], self.kids[np.repeat(self.kid_first[a[apart]] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]]

    def _add(self, centre: int, radius: float, size: int) -> int:
        self._made.append((centre, radius, size, len(self._order)))
        self._kids.append([])
        return len(self._made) - 1

    def _single(self, row: int) -> int:
        node = self._add(row, 0.0, 1)
        self._order.append(row)
        return node

    def _node(self, centre: int, rows: np.ndarray, scale: float, level: int) -> int:
        self.depth = max(self.depth, level)
        if len(rows) == 1:
            return self._single(int(rows[0]))
        radius = float(np.sqrt(np.maximum(0.0, 2 - 2 * (self.x[rows] @ self.x[centre])).max())) + SLACK
        node = self._add(centre, radius, len(rows))
        if len(rows) <= self.leaf or radius < 1e-5:
            self._kids[node] = [self._single(r) for r in rows.tolist()]
            return node
        while scale >= radius:
            scale /= 2
        owner = self.net(centre, rows, scale)
        order = np.argsort(owner, kind="stable")
        names, head = np.unique(owner[order], return_index=True)
        self._kids[node] = [self._node(int(c), some, scale / 2, level + 1) for c, some in zip(names, np.split(rows[order], head[1:]), strict=True)]
        return node

    def net(self, centre: int, rows: np.ndarray, step: float, block: int = 256) -> np.ndarray:
        """For each row the net point that covers it within ``step``; net points lie further apart than that. The parent's centre is
        one; rows are met a block at a time, first against the points so far, then among themselves."""
        near, all_x = 1 - step * step / 2, self.narrow if step > 0.01 else self.x  # radii are taken from ``x`` whatever covers
        points, owner, many = np.full(len(rows) + 1, centre), np.empty(len(rows), np.int64), 1
        x = all_x[rows]
        net = np.empty((len(rows) + 1, x.shape[1]), x.dtype)
        net[0] = all_x[centre]
        for at in range(0, len(rows), block):
            some, these = rows[at : at + block], x[at : at + block]
            cos = these @ net[:many].T
            best = cos.argmax(1)
            own = np.where(cos[np.arange(len(some)), best] >= near, points[best], -1)
            left = np.flatnonzero(own < 0)
            if len(left):
                new = these[left]
                covers = new @ new.T >= near
                covers |= covers.T
                np.fill_diagonal(covers, True)
                free = np.ones(len(left), bool)
                for i in np.flatnonzero(covers.sum(1) > 1).tolist():
                    if free[i]:
                        new = covers[i] & free
                        own[left[new]] = some[left[i]]
                        free &= ~new
                        free[i] = True
                chosen = left[free]
                own[chosen] = some[chosen]
                points[many : many + len(chosen)] = some[chosen]
                net[many : many + len(chosen)] = these[chosen]
                many += len(chosen)
            owner[at : at + block] = own
        return owner


class Links:
    """What a dual traversal finds: weighted degrees of both sides, component labels over ``x`` then ``y`` rows, and the number of
    distances it took, of heads or whole rows, and of whole rows. ``trees``: those of both sides, if they are there."""

    def __init__(self, x: np.ndarray, y: np.ndarray, mx: np.ndarray, my: np.ndarray, threshold: float, same: bool, trees: tuple[CoverTree, CoverTree] | None = None):
        self.x, self.ux = unit(x)
        self.y, self.uy = (self.x, self.ux) if same else unit(y)
        self.mx, self.my, self.threshold, self.same, self.reach = mx, my, threshold, same, chord(threshold)
        self.dx, self.dy = np.zeros(len(x), np.int64), np.zeros(len(y), np.int64)
        self.shift = 0 if same else len(x)
        self.label = np.arange(self.shift + len(y))
        self.edges, self.waiting, self.distances, self.whole = [], 0, 0, 0
        self.hx = heads(self.ux)
        self.hy = self.hx if same else heads(self.uy)
        if trees is None:
            tx = CoverTree(self.ux)
            trees = tx, tx if same else CoverTree(self.uy)
        self.trees = trees
        self.walk()
        self._join()

    def _edge(self, i: np.ndarray, j: np.ndarray) -> None:
        """Rows of ``x`` and ``y`` that are linked."""
        j = j + self.shift
        new = self.label[i] != self.label[j]
        if new.any():
            self.edges.append((i[new], j[new]))
            self.waiting += int(new.sum())
            if self.waiting > 200_000:
                self._join()

    def _join(self) -> None:
        if self.edges:
            low = min_labels(len(self.label), *(self.label[np.concatenate(e)] for e in zip(*self.edges, strict=True)))
            self.label = low[self.label]
            self.edges, self.waiting = [], 0

    def decide(self, i: np.ndarray, j: np.ndarray, cos: np.ndarray) -> None:
        """Pairs of rows with their cosine; what lies at the threshold is looked at again."""
        ok = cos >= self.threshold + UNSURE
        again = np.flatnonzero(~ok & (cos >= self.threshold - UNSURE))
        if len(again):
            a, b = self.x[i[again]], self.y[j[again]]
            ok[again] = np.einsum("ij,ij->i", a, b) / np.sqrt(np.einsum("ij,ij->i", a, a) * np.einsum("ij,ij->i", b, b)) >= self.threshold
        i, j = i[ok], j[ok]
        if len(i):
            np.add.at(self.dx, i, self.my[j])
            np.add.at(self.dy, j, self.mx[i])
            self._edge(i, j)

    def every(self, p: np.ndarray, q: np.ndarray, one: bool) -> None:
        """All rows of two nodes (or of one) are linked."""
        self._edge(np.full(len(q), p[0]), q)
        if one:
            self.dx[p] += self.mx[p].sum() - self.mx[p]
            return
        self._edge(p, np.full(len(p), q[0]))
        self.dx[p] += self.my[q].sum()
        self.dy[q] += self.mx[p].sum()

    def walk(self) -> None:
        tx, ty = self.trees
        if not len(tx.centre) or not len(ty.centre):
            return
        self.todo = [] if self.same else [(np.zeros(1, np.int64), np.zeros(1, np.int64))]
        own = [0] if self.same else []
        while own or self.todo:
            if own:
                p = own.pop()
                if 2 * tx.radius[p] <= self.reach - SLACK:
                    rows = tx.rows_of(p)
                    self.every(rows, rows, True)
                else:
                    own += self.product(p, p, True).tolist()
                continue
            a, b = self.todo.pop()
            ka, kb = tx.kid_count[a], ty.kid_count[b]
            wide = np.maximum(ka, 1) * np.maximum(kb, 1) >= 4096
            for p, q in zip(a[wide].tolist(), b[wide].tolist(), strict=True):
                self.product(p, q, False)
            a, b, ka, kb = a[~wide], b[~wide], ka[~wide], kb[~wide]
            left = (ka > 0) & ((kb == 0) | (tx.radius[a] >= ty.radius[b]))
            self.enter(tx, a[left], ka[left], b[left], False)
            self.enter(ty, b[~left], kb[~left], a[~left], True)

    def enter(self, tree: CoverTree, nodes: np.ndarray, many: np.ndarray, other: np.ndarray, swap: bool, most: int = 50_000) -> None:
        """Children of ``nodes`` against the node each was paired with, a bounded number of pairs at a time."""
        edge = np.cumsum(many)
        for lo, hi in zip(*_pieces(edge, most), strict=True):
            n = many[lo:hi]
            at = np.repeat(tree.kid_first[nodes[lo:hi]] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            a, b = tree.kids[at], np.repeat(other[lo:hi], n)
            a, b = (b, a) if swap else (a, b)
            tx, ty = self.trees
            cos = np.einsum("ij,ij->i", self.ux[tx.centre[a]], self.uy[ty.centre[b]])
            self.distances += len(cos)
            self.whole += len(cos)
            live = 2 - 2 * cos <= (self.reach + SLACK + tx.radius[a] + ty.radius[b]) ** 2
            self.settle(a[live], b[live], cos[live])

    def product(self, p: int, q: int, one: bool) -> np.ndarray:
        """All children of ``p`` against all of ``q``, single rows apart from the others; of one node every unordered pair once.
        Returns the children of ``p`` that were not taken row by row."""
        tx, ty = self.trees
        a = tx.opened(p, self.reach / 2)
        single, many = a[tx.size[a] == 1], a[tx.size[a] > 1]
        if one:
            self.rows(single, single, True)
            sides = ((single, many, False), (many, many, True))
        else:
            b = ty.opened(q, self.reach / 2)
            alone, more = b[ty.size[b] == 1], b[ty.size[b] > 1]
            self.rows(single, alone, False)
            sides = ((single, more, False), (many, alone, False), (many, more, False))
        for x, y, over in sides:
            if len(x) and len(y):
                self.matrix(x, y, over)
        return many

    def rows(self, a: np.ndarray, b: np.ndarray, over: bool, tall: int = 256, broad: int = 2048) -> None:
        """Single rows against single rows: heads first, whole rows for the pairs that these leave; whole rows at once where heads
        leave many. ``over``: only pairs above the diagonal."""
        i, j = self.trees[0].centre[a], self.trees[1].centre[b]
        hx, hy = self.hx[i], self.hy[j]
        least = np.float32(self.threshold - ROUGH)
        poor = not hx.shape[1]
        for s in range(0, len(i), tall):
            for t in range(s if over else 0, len(j), broad):
                si, tj = i[s : s + tall], j[t : t + broad]
                self.distances += len(si) * len(tj)
                if not poor:
                    at = np.flatnonzero(hx[s : s + tall] @ hy[t : t + broad].T >= least)
                    poor = 16 * len(at) > len(si) * len(tj)
                self.whole += len(si) * len(tj) if poor else len(at)
                if poor:
                    cos = (self.ux[si] @ self.uy[tj].T).ravel()
                    at = np.flatnonzero(cos >= self.threshold - UNSURE)
                    cos = cos[at]
                f, g = np.divmod(at, len(tj))
                if over:
                    above = s + f < t + g
                    f, g = f[above], g[above]
                    cos = cos[above] if poor else None
                if len(f):
                    self.decide(si[f], tj[g], cos if poor else np.einsum("ij,ij->i", self.ux[si[f]], self.uy[tj[g]]))

    def matrix(self, a: np.ndarray, b: np.ndarray, over: bool) -> None:
        """Nodes against nodes; ``over``: only pairs above the diagonal."""
        tx, ty = self.trees
        ca, cb, ra, rb = tx.centre[a], ty.centre[b], tx.radius[a] + (self.reach + SLACK), ty.radius[b]
        for s in range(0, len(a), 256):
            f = s if over else 0
            cos = self.ux[ca[s : s + 256]] @ self.uy[cb[f:]].T
            self.distances += cos.size
            self.whole += cos.size
            i, j = np.nonzero(2 - 2 * cos <= (ra[s : s + 256, None] + rb[None, f:]) ** 2)
            c = cos[i, j]
            i, j = i + s, j + f
            if over:
                keep_ = i < j
                i, j, c = i[keep_], j[keep_], c[keep_]
            self.settle(a[i], b[j], c)

    def settle(self, a: np.ndarray, b: np.ndarray, cos: np.ndarray) -> None:
        """Node pairs in reach: single rows are decided, large pairs wholly within the threshold counted, the others wait."""
        tx, ty = self.trees
        na, nb = tx.size[a], ty.size[b]
        row = (na == 1) & (nb == 1)
        self.decide(tx.centre[a[row]], ty.centre[b[row]], cos[row])
        a, b, cos, large = a[~row], b[~row], cos[~row], (na * nb)[~row] >= 64
        inside = large & (np.sqrt(np.maximum(0.0, 2 - 2 * cos)) + tx.radius[a] + ty.radius[b] <= self.reach - SLACK)
        for p, q in zip(a[inside].tolist(), b[inside].tolist(), strict=True):
            self.every(tx.rows_of(p), ty.rows_of(q), False)
        if not inside.all():
            self.todo.append((a[~inside], b[~inside]))


def _pieces(edge: np.ndarray, most: int) -> tuple[list[int], list[int]]:
    """Runs of items whose running total ``edge`` grows by about ``most`` each (one item at least)."""
    if not len(edge):
        return [], []
    cut = np.unique(np.searchsorted(edge, np.arange(0, edge[-1] + most, most)[1:], side="right").clip(1, len(edge)))
    cut = cut.tolist() if len(cut) and cut[-1] == len(edge) else [*cut.tolist(), len(edge)]
    return [0, *cut[:-1]], cut


class Block:
    """Classes of one block: their keys, counts, vectors and the tree over them, which is built once and travels with the keys."""

    def __init__(self, keys: list[bytes], m: np.ndarray, tree: CoverTree | None = None):
        self.keys, self.m, self.x = keys, m, matrix(keys)
        self.tree = tree or CoverTree(unit(self.x)[1])

    def pack(self) -> bytes:
        return pickle.dumps((b"".join(self.keys), np.fromiter(map(len, self.keys), np.int64, len(self.keys)), self.m, self.tree.pack()), 5)

    @classmethod
    def unpack(cls, body: bytes) -> Block:
        flat, sizes, m, tree = pickle.loads(body)
        ends = np.cumsum(sizes)
        return cls([flat[lo:hi] for lo, hi in zip((ends - sizes).tolist(), ends.tolist(), strict=True)], m, CoverTree.unpack(tree))

    def links(self, other: Block, threshold: float) -> dict[str, pa.Array]:
        """Links to another block, or of this one: rows ``a, n`` (links of a class) and ``a, b`` (forest)."""
        same = self is other
        found = Links(self.x, other.x, self.m, other.m, threshold, same, (self.tree, other.tree))
        n, keys = (found.dx + found.dy, self.keys) if same else (np.r_[found.dx, found.dy], self.keys + other.keys)
        a = [keys[i] for i in np.flatnonzero(n).tolist()]
        way = np.flatnonzero(found.label != np.arange(len(keys))).tolist()
        return {"a": pa.array(a + [keys[i] for i in way], pa.binary()), "b": pa.array([None] * len(a) + [keys[found.label[i]] for i in way], pa.binary()), "n": pa.array(n[n > 0].tolist() + [None] * len(way), pa.int64())}


def prepare(vectors: DataFrame) -> DataFrame:
    """``vec_id, key, dim``: the vector's doubles as bytes, null where it links with nothing."""

    def work(batches):
        for batch in batches:
            column = batch.column("embedding")
            sizes = np.array([-1 if v is None else v for v in pc.list_value_length(column).to_pylist()])
            flat = pc.cast(column.flatten(), pa.float64()).to_numpy(zero_copy_only=False)  # null components are not finite here
            ends = np.cumsum(np.maximum(sizes, 0))
            keys = []
            for n, e in zip(sizes.tolist(), ends.tolist(), strict=True):
                x = flat[e - max(n, 0) : e]
                ok = n > 0 and bool(np.isfinite(x).all()) and bool(x.any())
                with np.errstate(over="ignore"):
                    narrow = x.astype(np.float32)
                keys.append((b"4" + narrow.tobytes() if (narrow == x).all() else b"8" + x.tobytes()) if ok else None)
            dims = [n if k is not None else 0 for n, k in zip(sizes.tolist(), keys, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(keys, pa.binary()), pa.array(dims, pa.int32())], names=["vec_id", "key", "dim"])

    return vectors.selectExpr("cast(vec_id as long) vec_id", "embedding").mapInArrow(work, "vec_id long, key binary, dim int")


def matrix(keys: list[bytes]) -> np.ndarray:
    return np.stack([np.frombuffer(k, np.float32, offset=1).astype(np.float64) if k[:1] == b"4" else np.frombuffer(k, np.float64, offset=1) for k in keys])


def pivots_of(sample: np.ndarray, k: int) -> np.ndarray:
    """Farthest-point net of unit rows."""
    chosen = [0]
    away = 2 - 2 * (sample @ sample[0])
    while len(chosen) < min(k, len(sample)):
        chosen.append(int(away.argmax()))
        away = np.minimum(away, 2 - 2 * (sample @ sample[chosen[-1]]))
    return sample[chosen]


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` of every vector."""
    spark = ship(vectors.sparkSession)
    rows = keep(prepare(vectors), "vectors")
    classes = keep(rows.filter("key is not null").groupBy("key").agg(F.min("vec_id").alias("first"), F.count("*").alias("m"), F.min("dim").alias("dim")).withColumn("cls", F.xxhash64("key")), "classes")
    found = _links(spark, classes, threshold, block)
    degree = found.filter("n is not null").groupBy(F.col("a").alias("key")).agg(F.sum("n").alias("n"))
    root = graph.components(found.filter("b is not null").select("a", "b")).select(F.col("node").alias("key"), "root")
    own = classes.select("key", "first", "m").join(degree, "key", "left").join(root, "key", "left").select("key", "first", (F.col("m") - 1 + F.coalesce("n", F.lit(0))).alias("n_links"), F.coalesce("root", "key").alias("root"))
    least = own.groupBy("root").agg(F.min("first").alias("component_id"))
    per = own.join(least, "root").select("key", "n_links", "component_id")
    out = rows.join(per, "key", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


def top_net(classes: DataFrame, block: int) -> dict[int, np.ndarray]:
    """Pivots of each vector length in a bounded sample (least hashes first): about one a block of its classes, at most ``PIVOTS`` in
    all. A length outside the sample has none and is one cell."""
    total = classes.count()
    sample: dict[int, list[bytes]] = {}
    for r in classes.orderBy("cls", "key").limit(SAMPLE).select("key", "dim").collect():
        sample.setdefault(r["dim"], []).append(bytes(r["key"]))
    seen = sum(map(len, sample.values()))
    wish = {d: max(1, min(-(-len(k) * total // (seen * block)), PIVOTS * len(k) // seen)) for d, k in sample.items()}
    return {d: pivots_of(unit(matrix(k))[1], wish[d]) for d, k in sample.items()}


def _links(spark, classes: DataFrame, threshold: float, block: int) -> DataFrame:
    """Rows ``a, n`` (links of class ``a``) and ``a, b`` (forest) among classes of equal length."""
    nets = top_net(classes, block)
    shared = spark.sparkContext.broadcast(nets)  # at most SAMPLE rows, however many vectors

    def assign(batches):
        for batch in batches:
            dim = batch.column("dim").to_numpy()
            cell, away = np.zeros(len(dim), np.int32), np.full(len(dim), 2.0)
            for d in np.unique(dim).tolist():
                if d in shared.value:
                    at = np.flatnonzero(dim == d)
                    cos = unit(matrix([batch.column("key")[i].as_py() for i in at.tolist()]))[1] @ shared.value[d].T
                    cell[at] = cos.argmax(1)
                    away[at] = np.sqrt(np.maximum(0.0, 2 - 2 * cos.max(1)))
            yield pa.RecordBatch.from_arrays([batch.column("key"), batch.column("m"), batch.column("cls"), pa.array(dim), pa.array(cell), pa.array(away)], names=["key", "m", "cls", "dim", "cell", "away"])

    placed = keep(classes.select("key", "m", "cls", "dim").mapInArrow(assign, "key binary, m long, cls long, dim int, cell int, away double"), "cells")
    cells, weight = {}, 0
    for r in placed.groupBy("dim", "cell").agg(F.count("*"), F.max("away"), F.sum(F.length("key"))).collect():
        cells[r[0], r[1]] = r[2], r[3]
        weight += r[4] + 40 * r[2]
    split = {c: max(1, -(-n // block)) for c, (n, _) in cells.items()}
    base, total = {}, 0
    for c in sorted(cells):
        base[c], total = total, total + split[c]
    # a block is sent once to each group of blocks: as few groups as their bytes and the session's parallelism allow
    tiles = min(total, max(-(-weight // TILE), int((4 * width(spark)) ** 0.5) + 1))
    by_dim: dict[int, list] = {}
    for c in cells:
        by_dim.setdefault(c[0], []).append(c)

    def may_meet(c, d) -> bool:
        if c[0] not in nets:
            return True
        gap = chord(float(nets[c[0]][c[1]] @ nets[c[0]][d[1]]))
        return gap - cells[c][1] - cells[d][1] <= chord(threshold) + 1e-6

    meets = {c: [d for d in by_dim[c[0]] if may_meet(c, d)] for c in cells}

    def gather(batches):
        held: dict[int, tuple[list, list]] = {}

        def flush():
            for unit_, (ids, ms) in held.items():
                yield pa.RecordBatch.from_arrays([pa.array([unit_], pa.int64()), pa.array([ids], pa.list_(pa.binary())), pa.array([np.array(ms, np.int64).tobytes()], pa.binary())], names=["unit", "ids", "ms"])
            held.clear()

        size = 0
        for batch in batches:
            for key, m, cls, dim, cell in zip(*(batch.column(c).to_pylist() for c in ("key", "m", "cls", "dim", "cell")), strict=True):
                cell = dim, cell
                ids, ms = held.setdefault(base[cell] + cls % split[cell], ([], []))
                ids.append(key)
                ms.append(m)
            size += batch.num_rows
            if size >= 4 * block:
                yield from flush()
                size = 0
        yield from flush()

    def build(table: pa.Table) -> pa.Table:
        made = Block([k for ids in table.column("ids").to_pylist() for k in ids], np.concatenate([np.frombuffer(ms, np.int64) for ms in table.column("ms").to_pylist()]))
        own = made.links(made, threshold)
        n = len(own["a"])
        return pa.table({k: pa.concat_arrays([v, pa.nulls(1, v.type)]) for k, v in own.items()} | {"unit": pa.array([None] * n + [table.column("unit")[0].as_py()], pa.int64()), "body": pa.array([None] * n + [made.pack()], pa.binary())})

    def send(batches):
        for batch in batches:
            for i, b in enumerate(batch.column("unit").to_pylist()):
                cell, mine = owner[b], b % tiles
                for other in sorted({(base[d] + s) % tiles for d in meets[cell] for s in range(split[d]) if base[d] + s != b}):
                    yield pa.RecordBatch.from_arrays([pa.array([min(mine, other) * tiles + max(mine, other)], pa.int64()), *(batch.column(c).slice(i, 1) for c in ("unit", "body"))], names=["tile", "unit", "body"])

    def meet(table: pa.Table) -> pa.Table:
        left, right = divmod(table.column("tile")[0].as_py(), tiles)
        bodies = dict(zip(table.column("unit").to_pylist(), table.column("body"), strict=True))
        out = [pa.table({"a": pa.array([], pa.binary()), "b": pa.array([], pa.binary()), "n": pa.array([], pa.int64())})]
        for u in sorted(bodies):
            if u % tiles == left:
                others = [v for v in sorted(bodies) if v % tiles == right and (left < right or u < v) and owner[v] in meets[owner[u]]]
                one = Block.unpack(bodies[u].as_py()) if others else None
                out += [pa.table(one.links(Block.unpack(bodies[v].as_py()), threshold)) for v in others]
        return pa.concat_tables(out).combine_chunks()

    owner = {base[c] + s: c for c in cells for s in range(split[c])}
    blocks = keep(placed.mapInArrow(gather, "unit long, ids array<binary>, ms binary").groupBy("unit").applyInArrow(build, "a binary, b binary, n long, unit long, body binary"), "blocks")
    found = blocks.filter("unit is null").select("a", "b", "n")
    if total > 1:
        made = blocks.filter("unit is not null").select("unit", "body")
        pairs = made.mapInArrow(send, "tile long, unit long, body binary")
        found = keep(found.unionByName(pairs.groupBy("tile").applyInArrow(meet, "a binary, b binary, n long")), "links")
        drop(blocks)
    drop(placed)
    return found
