"""Exact top-k by inner product with M-trees: paged metric nodes, covering radii, parent distances, best-first search.

Vectors of whole numbers get one more coordinate that makes all of a tree's vectors equally long; then the largest inner
products are the nearest points. Vectors are dealt into cells of bounded size by a hash, a tree a cell. A search visits
nodes by their least possible distance, and passes over entries whose stored distance to the parent already proves them
too far. Trees are built once and stored with their pages, radii and parent distances. A block of queries first searches
one tree; the k-th best score found there is the opening radius for all other trees, which give at most k better rows each.

Edge cases: vectors that are null, empty or hold null or non-finite components, and rows with a null id, take no part;
vectors meet others of their dimension only; equal scores go to the smaller id; repeated rows of an id are all its own;
fewer than k candidates give fewer rows; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import file_system, run_folder, written

CELL, PAGE, FAN, QUERIES = 2048, 256, 8, 256
#: Trees of a task on average: it reads the query blocks once for all of them.
TREES = 64
_SLACK = 1e-6


class Tree:
    """Pages in arrays: each node has entries (object, distance to the node's own object, covering radius, child or -1)."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, nodes: list | None = None):
        """Builds the tree, or takes its nodes as stored; stored ids and vectors are in order."""
        order = np.argsort(ids, kind="stable") if nodes is None else slice(None)
        self.ids, self.vectors = ids[order], vectors[order]
        self.dots = _exact(self.vectors)
        self.square = self._own_squares()
        #: Most rows that share an id: so many of a query's own may stand among its best.
        self.most_alike = int(np.unique(self.ids, return_counts=True)[1].max(initial=0))
        self.length = float(max(self.square, default=0))
        self.lift = np.sqrt(np.maximum(self.length - np.array(self.square, np.float64), 0))
        self.nodes: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = nodes or []
        self.root = -1 if not len(ids) else 0 if nodes else self._build(np.arange(len(ids)), None)
        #: Each page's vectors lie together, so that an unpruned page is one product.
        self.pages = [self.vectors[node[0]] for node in self.nodes]

    def stored(self) -> dict[str, bytes]:
        """Ids, vectors and pages as bytes."""
        parts = [np.concatenate([n[i] for n in self.nodes]) if self.nodes else np.zeros(0) for i in range(4)]
        return {
            "ids": self.ids.astype("<i8").tobytes(), "vectors": packed(self.vectors), "entries": np.array([len(n[0]) for n in self.nodes], "<i4").tobytes(),
            "objects": parts[0].astype("<i4").tobytes(), "parents": parts[1].astype("<f8").tobytes(), "radii": parts[2].astype("<f8").tobytes(), "children": parts[3].astype("<i4").tobytes(),
        }

    @classmethod
    def load(cls, dim: int, ids: bytes, vectors: bytes, entries: bytes, objects: bytes, parents: bytes, radii: bytes, children: bytes) -> "Tree":
        cuts = np.cumsum(np.frombuffer(entries, "<i4"))[:-1]
        parts = [np.split(np.frombuffer(data, kind), cuts) for data, kind in ((objects, "<i4"), (parents, "<f8"), (radii, "<f8"), (children, "<i4"))]
        return cls(np.frombuffer(ids, "<i8"), _matrix(unpacked(vectors, len(ids) // 8, dim)), list(zip(*parts, strict=True)))

    def _own_squares(self) -> list:
        if self.vectors.dtype == np.float64:
            return np.einsum("ij,ij->i", self.vectors, self.vectors).tolist()
        return [int(sum(int(x) * int(x) for x in v)) for v in self.vectors]

    def _between(self, a: int, others: np.ndarray) -> np.ndarray:
        v = self.vectors.astype(np.float64)
        d = ((v[others] - v[a]) ** 2).sum(axis=1) + (self.lift[others] - self.lift[a]) ** 2
        return np.sqrt(d)

    def _build(self, members: np.ndarray, parent: int | None) -> int:
        """Bulk load: spread pivots take their nearest members, until a page holds them."""
        at = len(self.nodes)
        self.nodes.append(None)
        if len(members) <= PAGE:
            d = self._between(parent, members) if parent is not None else np.zeros(len(members))
            self.nodes[at] = (members, d, np.zeros(len(members)), np.full(len(members), -1))
            return at
        pivots = [int(members[0])]
        near = self._between(pivots[0], members)
        owner = np.zeros(len(members), np.int64)
        while len(pivots) < FAN and near.max() > 0:
            new = int(members[int(near.argmax())])
            d = self._between(new, members)
            closer = d < near
            near[closer], owner[closer] = d[closer], len(pivots)
            pivots.append(new)
        if len(pivots) == 1:  # all equal: pages in order
            owner = np.arange(len(members)) * FAN // len(members)
            pivots = [int(members[np.flatnonzero(owner == i)[0]]) for i in range(FAN)]
        children, radii = [], []
        for i, p in enumerate(pivots):
            own = members[owner == i]
            radii.append(float(self._between(p, own).max()))
            children.append(self._build(own, p))
        objects = np.array(pivots)
        d = self._between(parent, objects) if parent is not None else np.zeros(len(objects))
        self.nodes[at] = (objects, d, np.array(radii), np.array(children))
        return at

    def search(self, query: np.ndarray, own: int, k: int, floor: int | None = None) -> tuple[list[tuple[int, int]], int]:
        """((score, id) of the k best, ties to the smaller id; distances computed). Entries of id `own` and scores under `floor` are passed over."""
        if self.root < 0:
            return [], 0
        q = query.astype(np.float64)
        square = float((q * q).sum())
        best: list[tuple[int, int, int]] = []
        computed = 0

        def radius_of(score: int) -> float:
            return max(square + self.length - 2 * score, 0) ** 0.5 * (1 + _SLACK) + _SLACK

        reach = float("inf") if floor is None else radius_of(floor)
        # no score exceeds the product of the lengths
        if floor is not None and floor > (square * self.length) ** 0.5 * (1 + _SLACK) + _SLACK:
            return [], 0
        queue: list[tuple[float, int, float]] = [(0.0, self.root, -1.0)]
        while queue:
            low, node, to_parent = heapq.heappop(queue)
            if low > reach:
                break
            objects, d, radius, child = self.nodes[node]
            page = self.pages[node]
            if to_parent >= 0 and reach < float("inf"):
                ok = np.flatnonzero(np.abs(to_parent - d) - radius <= reach)
                if not len(ok):
                    continue
                if len(ok) < len(objects):
                    objects, radius, child, page = objects[ok], radius[ok], child[ok], page[ok]
            score = self.dots(page, query)
            computed += len(objects)
            if child[0] >= 0:
                dist = np.sqrt(np.maximum(square + self.length - 2 * score.astype(np.float64), 0))
                for s, x, c in zip(np.maximum(dist - radius, 0).tolist(), dist.tolist(), child.tolist(), strict=True):
                    if s <= reach:
                        heapq.heappush(queue, (s, c, x))
                continue
            if len(best) == k:
                few = np.flatnonzero(score >= best[0][0])
            elif floor is not None:
                few = np.flatnonzero(score >= floor)
            elif len(score) > 4 * k:  # the own row may be among the best, so one more than k
                few = np.flatnonzero(score >= np.partition(score, -k - self.most_alike)[-k - self.most_alike]) if len(score) > k + self.most_alike else np.arange(len(score))
            else:
                few = np.arange(len(score))
            for s, i in zip(score[few].tolist(), objects[few].tolist(), strict=True):
                key = int(self.ids[i])
                item = (int(s), -key, i)
                if key != own and (len(best) < k or item > best[0]):
                    heapq.heappushpop(best, item) if len(best) == k else heapq.heappush(best, item)
            if len(best) == k:
                reach = radius_of(best[0][0])
        return [(s, -i) for s, i, _ in sorted(best, reverse=True)], computed


def _exact(vectors: np.ndarray):
    """Inner products as exact whole numbers: in doubles where they cannot round, else in Python's integers."""
    if vectors.dtype == np.float64:
        return lambda page, q: (page @ q).astype(np.int64)
    return lambda page, q: np.array([sum(int(a) * int(b) for a, b in zip(v, q, strict=True)) for v in page], object)


def packed(vectors: np.ndarray) -> bytes:
    """Whole numbers in two bytes each, if all fit, else in eight."""
    small = vectors.size == 0 or float(np.abs(vectors).max()) < 2**15
    return vectors.astype("<i2" if small else "<i8").tobytes()


def unpacked(data: bytes, rows: int, dim: int) -> np.ndarray:
    kind = "<i2" if len(data) == 2 * rows * dim else "<i8"
    return np.frombuffer(data, kind).astype(np.int64).reshape(rows, dim)


def whole_vectors(table: DataFrame, scale: int = 256) -> DataFrame:
    """(vec_id, v): floor(scale * x) of each component, as double."""
    x = F.transform("embedding", lambda c: c.cast("double"))
    fine = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0)
    clean = ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return table.where(fine).where(F.coalesce(clean, F.lit(False))).select("vec_id", F.transform(x, lambda c: F.floor(F.lit(float(scale)) * c)).alias("v"))


def _matrix(rows) -> np.ndarray:
    m = rows if isinstance(rows, np.ndarray) and rows.ndim == 2 else np.array([list(r) for r in rows], dtype=np.int64)
    small = m.size == 0 or float(np.abs(m).max()) ** 2 * m.shape[1] < 2**52
    return m.astype(np.float64) if small else m


_PAGES = ("ids", "vectors", "entries", "objects", "parents", "radii", "children")
#: Stands for no opening score.
_NO_FLOOR = -(1 << 63)


def build_trees(data: DataFrame, cells: int) -> DataFrame:
    """A written table of trees with their pages, a row a cell; data is (vec_id, v, dim)."""

    def build(frame):
        import pandas as pd

        tree = Tree(frame["vec_id"].to_numpy(np.int64), _matrix(frame["v"]))
        return pd.DataFrame({"dim": frame["dim"].iloc[:1], "cell": frame["cell"].iloc[:1], **{c: [x] for c, x in tree.stored().items()}})

    dealt = data.withColumn("cell", F.pmod(F.xxhash64("vec_id", "v"), F.lit(cells)))
    return written(dealt.groupBy("dim", "cell").applyInPandas(build, "dim int, cell long, " + ", ".join(f"{c} binary" for c in _PAGES)), "tree-pages")


def bundled(asked: DataFrame, blocks: int) -> str:
    """The shared folder of query blocks, a row each: dim, block, q_ids, q_vectors, floors; asked is (vec_id, v, dim, floor)."""

    def bundle(frame):
        import pandas as pd

        m = np.array([list(r) for r in frame["v"]], np.int64)
        return pd.DataFrame({"dim": frame["dim"].iloc[:1], "block": frame["block"].iloc[:1], "q_ids": [frame["vec_id"].to_numpy(np.int64).tobytes()], "q_vectors": [packed(m)], "floors": [frame["floor"].to_numpy(np.int64).tobytes()]})

    folder = run_folder(asked.sparkSession, "query-blocks") + "/table"
    grouped = asked.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(blocks)))
    grouped.groupBy("dim", "block").applyInPandas(bundle, "dim int, block long, q_ids binary, q_vectors binary, floors binary").write.parquet(folder)
    return folder


def _asked_of(folder: str):
    """The query blocks in the files of a folder, one after another: a task never holds more than one row group of them."""
    import pyarrow.parquet as pq
    from pyarrow import fs as pafs

    fs, inside = file_system(folder)
    for path in sorted(f.path for f in fs.get_file_info(pafs.FileSelector(inside)) if f.base_name.endswith(".parquet")):
        with fs.open_input_file(path) as f:
            for batch in pq.ParquetFile(f).iter_batches(batch_size=8):
                yield from batch.to_pylist()


def visited(trees: DataFrame, folder: str, cells: int, k: int, home: bool) -> DataFrame:
    """(query_id, vec_id, score): at most k rows a tree and query, none under the query's floor.

    The blocks lie in `folder`, which all executors share; every task reads them past its own trees, a bounded number of
    which it holds at once. So no pair of a block and a tree is ever a row, in a shuffle or in a broadcast. With `home`
    a block meets its home tree only, else all others.
    """

    def visit(frames):
        import pandas as pd

        for frame in frames:
            held = {}
            for row in frame.itertuples(index=False):
                held.setdefault(int(row.dim), {})[int(row.cell)] = Tree.load(row.dim, *(getattr(row, c) for c in _PAGES))
            for sent in _asked_of(folder):
                near = held.get(sent["dim"], {})
                if not near:
                    continue
                ids, floors = np.frombuffer(sent["q_ids"], np.int64).tolist(), np.frombuffer(sent["floors"], np.int64).tolist()
                asks = unpacked(sent["q_vectors"], len(ids), sent["dim"])
                out = []
                for cell, tree in near.items():
                    if (cell == sent["block"] % cells) != home:
                        continue
                    most = max(float(np.abs(asks).max()), float(np.abs(tree.vectors).max()))
                    if most * most * sent["dim"] >= 2**52 and tree.vectors.dtype == np.float64:
                        tree = near[cell] = Tree(tree.ids, tree.vectors.astype(np.int64), tree.nodes)
                    for q, v, low in zip(ids, asks if tree.vectors.dtype == np.int64 else asks.astype(np.float64), floors, strict=True):
                        out += [(q, i, s) for s, i in tree.search(v, q, k, None if low == _NO_FLOOR else low)[0]]
                if out:
                    yield pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    spread = max(-(-cells // TREES), min(cells, 2 * trees.sparkSession.sparkContext.defaultParallelism))
    return trees.select("dim", "cell", *_PAGES).repartition(spread).mapInPandas(visit, "query_id long, vec_id long, score long")


def search(table: DataFrame, queries: DataFrame, k: int = 5, cell: int = CELL, block: int = QUERIES) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k largest inner products; table and queries are (vec_id, v).

    Every block of queries meets the stored pages of every tree: both are of bounded size, and a pair of them gives at
    most k rows a query.
    """
    data = written(table.select("vec_id", "v", F.size("v").alias("dim")), "vectors")
    cells = max(1, -(-data.count() // cell))
    asked = written(queries.select("vec_id", "v", F.size("v").alias("dim")), "queries")
    blocks = max(1, -(-asked.count() // block))
    trees = build_trees(data, cells)
    opening = written(visited(trees, bundled(asked.withColumn("floor", F.lit(_NO_FLOOR)), blocks), cells, k, True), "opening")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = opening.withColumn("rank", F.row_number().over(order))
    floors = ranked.where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"), F.col("score").alias("floor"))
    again = bundled(asked.join(floors, "vec_id", "left").withColumn("floor", F.coalesce("floor", F.lit(_NO_FLOOR))), blocks)
    found = opening.unionByName(visited(trees, again, cells, k, False))
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
