"""Exact top-k search by an M-tree over all rows.

Inner products become distances: with M the longest norm of all vectors, x gets one
more component sqrt(M^2 - |x|^2) and a query a zero, so the largest product is the
least Euclidean distance. Pivots, a bounded sample of rows, cut the space: a row
belongs to the block of the nearest one, and a block with too many rows is dealt over
several. A block is one subtree of bounded size. A node is a page: a routing vector, a
covering radius and, for each entry, its vector (or child page) with its distance to
the routing one. The blocks' roots are the tree's upper level.

A query first searches the block where it would lie itself, which gives a bound for
its k-th result. Then it goes to those other blocks alone whose ball can hold anything
as near. Many queries go through a block together: at each page those stay that its ball
can serve, by |d(q, parent) - d(child, parent)| - radius before a distance is computed
and by d(q, child) - radius after, nearest pages first. What is left at a leaf is one
product of matrices. ``Tree.search`` is the same search for one query, best first. Scores
are products of integers, so they are exact; bounds keep a margin for rounding. ``work``
counts the distances that a search computes.

A block is one row, a list of queries another. A task gets the queries of one part (near
each other, PART_QUERIES or so) and takes up to GROUP_BLOCKS blocks or so one after the
other, so blocks move once for each part, queries once for each group of blocks, and
memory doesn't follow the input. Nothing is collected but a row for each length of
vectors and MAX_PIVOTS pivots. Results are merged by a window.

Defined cases: null vectors, empty ones, ones with null or non-finite components and
null ids take no part; vectors meet those of their own length; a query's own id is no
candidate; a repeated candidate row counts as often as it is there; a repeated query
id is answered once, for its least vector.
"""

from __future__ import annotations

import contextlib
import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, arrow_rows, release

BLOCK_ROWS, PAGE_ROWS, FANOUT = 4096, 128, 16
#: Pivots for vectors of one length, at most; blocks of more rows are dealt over several.
MAX_PIVOTS = 2048
#: Queries in a list, in a part and in one product; roots that meet a part in a task.
CHUNK_ROWS, PART_QUERIES, SLICE_QUERIES, ROOT_ROWS = 512, 16384, 2048, 2048
#: Blocks that a task searches one after the other, at most; tasks wanted, and at most; blocks in an Arrow batch; results held besides 2 k a query.
GROUP_BLOCKS, MIN_GROUPS, MAX_TASKS, BATCH_BLOCKS, MOST_FOUND = 16, 64, 2000, 4, 1_000_000
#: A block's number: length of vectors, pivot, share.
_DIM, _PIVOT = 2**40, 2**24
_BLOCK = "block long, route binary, radius double, nodes binary, routes binary, ids binary, vectors binary"
_PAGE = np.dtype([("parent", "<i4"), ("start", "<i4"), ("size", "<i4"), ("radius", "<f8"), ("inner", "<f8"), ("to_parent", "<f8")])


def scaled(col: str, factor: float = 64.0) -> Column:
    """Whole-number components, or null where the vector can't take part."""
    bad = F.exists(col, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when((F.size(col) > 0) & ~bad, F.transform(col, lambda x: F.floor(F.lit(factor) * x.cast("double")).cast("long")))


def lifted(v: np.ndarray, longest: float) -> np.ndarray:
    """Vectors with the component that turns products into distances."""
    return np.hstack([v, np.sqrt(np.maximum(0.0, longest - (v * v).sum(axis=1)))[:, None]])


def build(ids: np.ndarray, v: np.ndarray, longest: float) -> list[dict]:
    """Pages of one tree, parents first; the root is page 0."""
    x, pages = lifted(v, longest), []

    def add(rows: np.ndarray, parent: int, parent_route: np.ndarray | None) -> None:
        route = x[rows].mean(axis=0)
        far = np.sqrt(((x[rows] - route) ** 2).sum(axis=1))
        k = len(pages)
        page = {"node": k, "parent": parent, "leaf": len(rows) <= PAGE_ROWS, "route": route.tobytes(), "radius": float(far.max()), "to_parent": 0.0 if parent_route is None else float(np.sqrt(((route - parent_route) ** 2).sum())), "ids": b"", "vectors": b"", "spread": b""}
        pages.append(page)
        if page["leaf"]:
            page |= {"ids": ids[rows].tobytes(), "vectors": v[rows].tobytes(), "spread": far.tobytes()}
            return
        n = min(FANOUT, -(-len(rows) // PAGE_ROWS))
        pivot = [int(far.argmax())]
        near = np.sqrt(((x[rows] - x[rows[pivot[0]]]) ** 2).sum(axis=1))
        own = np.zeros(len(rows), np.int64)
        for c in range(1, n):
            if near.max() == 0:
                break
            pivot.append(int(near.argmax()))
            d = np.sqrt(((x[rows] - x[rows[pivot[-1]]]) ** 2).sum(axis=1))
            own[d < near] = c
            near = np.minimum(near, d)
        if len(pivot) == 1 or np.bincount(own).max() > 0.9 * len(rows):  # equal or nearly equal vectors: cut anywhere
            own = np.argsort(np.argsort(far, kind="stable"), kind="stable") * n // len(rows)
        for c in np.unique(own):
            add(rows[own == c], k, route)

    add(np.argsort(ids, kind="stable"), -1, None)
    return pages


class Tree:
    def __init__(self, pages: list[dict], dim: int, longest: float):
        self.longest = longest
        self.pages = sorted(pages, key=lambda p: p["node"])
        self.radius = np.array([p["radius"] for p in self.pages])
        self.to_parent = np.array([p["to_parent"] for p in self.pages])
        self.route = np.array([np.frombuffer(p["route"]) for p in self.pages])
        self.child: list[list[int]] = [[] for _ in self.pages]
        for p in self.pages[1:]:
            self.child[p["parent"]].append(p["node"])
        self.children = [np.array(c, np.int64) for c in self.child]
        self.ids = [np.frombuffer(p["ids"], np.int64) for p in self.pages]
        self.vectors = [np.frombuffer(p["vectors"]).reshape(-1, dim) for p in self.pages]
        self.spread = [np.frombuffer(p["spread"]) for p in self.pages]

    def search(self, own: int, q: np.ndarray, k: int, bound: float | None = None) -> tuple[np.ndarray, np.ndarray, int]:
        """Ids and scores of the k best entries other than ``own``, best first, ties to the least id; and distances computed.

        Entries below ``bound`` don't matter.
        """
        norm = float(q @ q)
        top_ids, top = np.empty(0, np.int64), np.empty(0)
        reach = np.inf if bound is None else reached(norm, self.longest, bound)  # distance of the k-th result
        up = np.append(q, 0.0)
        d = float(np.sqrt(((self.route[0] - up) ** 2).sum()))
        queue, computed = [(max(0.0, d - self.radius[0]), 0, d)], 1
        while queue:
            low, node, d = heapq.heappop(queue)
            if low > reach:
                break
            if not self.pages[node]["leaf"]:
                c = self.children[node]
                c = c[np.abs(d - self.to_parent[c]) - self.radius[c] <= reach]
                computed += len(c)
                far = np.sqrt(((self.route[c] - up) ** 2).sum(axis=1))
                for n, dn, ln in zip(c.tolist(), far.tolist(), np.maximum(0.0, far - self.radius[c]).tolist(), strict=True):
                    if ln <= reach:
                        heapq.heappush(queue, (ln, n, dn))
                continue
            ids, v = self.ids[node], self.vectors[node]
            open_ = np.abs(d - self.spread[node]) <= reach
            if not open_.all():
                ids, v = ids[open_], v[open_]
            computed += len(ids)
            score = v @ q
            good = ids != own
            if len(top) == k:
                good &= score >= top[-1]
            if bound is not None:
                good &= score >= bound
            if not good.any():
                continue
            top_ids, top = np.concatenate([top_ids, ids[good]]), np.concatenate([top, score[good]])
            order = np.lexsort((top_ids, -top))[:k]
            top_ids, top = top_ids[order], top[order]
            if len(top) == k:
                reach = min(reach, reached(norm, self.longest, float(top[-1])))
        return top_ids, top, computed


def reached(norm: float, longest: float, score: float) -> float:
    """The distance at which a product of ``score`` lies, with a margin for rounding."""
    return math.sqrt(max(0.0, norm + longest - 2 * score) + 1e-7 * (1 + longest + norm))


def _vectors(rows: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    v = rows.select(F.col(id_col).cast("long").alias("vec_id"), scaled(vector_col).alias("v")).where("vec_id is not null and v is not null")
    return v.withColumn("dim", F.size("v"))


def _pivots(data: DataFrame, sizes: dict[int, int]) -> dict[int, np.ndarray]:
    """For each length of vectors a row for every BLOCK_ROWS of them, MAX_PIVOTS at most: those with the least hashes."""
    spark = data.sparkSession
    want = [(d, min(MAX_PIVOTS, -(-n // BLOCK_ROWS)), min(1.0, (2 * min(MAX_PIVOTS, -(-n // BLOCK_ROWS)) + 200) / n)) for d, n in sizes.items()]
    rows = spark.createDataFrame([(d, n, int(x * 2.0**63) if x < 1 else 2**63 - 1) for d, n, x in want], "dim int, n long, bound long")
    near = data.withColumn("_h", F.xxhash64("vec_id").bitwiseAND(F.lit(2**63 - 1))).join(F.broadcast(rows), "dim").where("_h <= bound")  # a row for each length
    least = Window.partitionBy("dim").orderBy("_h", "vec_id", "v")
    found = near.withColumn("_r", F.row_number().over(least)).where("_r <= n").select("dim", "v").collect()
    return {d: np.array([r.v for r in found if r.dim == d], np.float64).reshape(-1, d) for d in sizes}


def narrow(longest: float) -> np.dtype:
    """The smallest type that holds the components of all vectors of a length."""
    most = math.sqrt(longest)
    return np.dtype("<i1" if most < 127 else "<i2" if most < 32767 else "<i4" if most < 2**31 - 1 else "<f8")


def exact(longest: float) -> type:
    """Products are sums of whole numbers below ``longest``: singles hold them up to 2**24."""
    return np.float32 if longest < 2**24 else np.float64


def _placed(data: DataFrame, pivots: dict[int, np.ndarray], longest: dict[int, float]) -> DataFrame:
    """``dim, vec_id, v, pivot``: rows as bytes with the number of the nearest pivot."""
    up = {d: lifted(p, longest[d]) for d, p in pivots.items()}
    schema = pa.schema([("dim", pa.int32()), ("vec_id", pa.int64()), ("v", pa.binary()), ("pivot", pa.int64())])

    def each(part: pa.RecordBatch) -> dict[str, list]:
        dims = part.column("dim").to_numpy()
        v, own, held = part.column("v"), np.zeros(part.num_rows, np.int64), np.empty(part.num_rows, object)
        at, flat = v.offsets.to_numpy(), v.values.to_numpy(zero_copy_only=False).astype(np.float64)
        for d in np.unique(dims).tolist():
            rows, kind = np.flatnonzero(dims == d), narrow(longest[d])
            x = flat[at[rows][:, None] + np.arange(d)]
            raw, n = x.astype(kind).tobytes(), d * kind.itemsize
            held[rows] = [raw[i : i + n] for i in range(0, len(raw), n)]
            if len(up.get(d, ())) > 1:
                own[rows] = ((up[d] ** 2).sum(axis=1) - 2 * lifted(x, longest[d]) @ up[d].T).argmin(axis=1)
        return {"dim": part.column("dim"), "vec_id": part.column("vec_id"), "v": pa.array(held, pa.binary()), "pivot": own}

    return data.select("dim", "vec_id", "v").mapInArrow(arrow_rows(each, schema, 4096, raw=True), "dim int, vec_id long, v binary, pivot long")


def packed(ids: np.ndarray, v: np.ndarray, longest: float) -> dict[str, bytes | float]:
    """A block as one row: its pages in order, and the entries of all leaves one after the other."""
    pages = build(ids, v, longest)
    nodes, at = np.zeros(len(pages), _PAGE), 0
    for k, p in enumerate(pages):
        far = np.frombuffer(p["spread"])
        nodes[k] = (p["parent"], at, len(far), p["radius"], far.min() if len(far) else 0.0, p["to_parent"])
        at += len(far)
    vectors = np.frombuffer(b"".join(p["vectors"] for p in pages)).astype(narrow(longest))
    return {"route": pages[0]["route"], "radius": pages[0]["radius"], "nodes": nodes.tobytes(), "routes": b"".join(p["route"] for p in pages), "ids": b"".join(p["ids"] for p in pages), "vectors": vectors.tobytes()}


def _blocks(placed: DataFrame, longest: dict[int, float]) -> DataFrame:
    """All blocks; a block is (dim, pivot, share of the pivot's rows) in one number."""
    rows = placed.repartition("block").sortWithinPartitions("block").select("block", "vec_id", "v")
    schema = pa.schema([("block", pa.int64()), ("route", pa.binary()), ("radius", pa.float64()), ("nodes", pa.binary()), ("routes", pa.binary()), ("ids", pa.binary()), ("vectors", pa.binary())])

    def to_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, held = None, [], []

        def finish() -> Iterator[pa.RecordBatch]:
            if held:
                dim = now // _DIM
                v = np.frombuffer(b"".join(held), narrow(longest[dim])).reshape(-1, dim).astype(np.float64)
                yield pa.RecordBatch.from_pylist([{"block": now} | packed(np.concatenate(ids), v, longest[dim])], schema=schema)

        for batch in batches:
            block, own = batch.column("block").to_numpy(), batch.column("vec_id").to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(block)]
            for x, y in zip(cuts[:-1], cuts[1:], strict=True):
                if x == y:
                    continue
                if block[x] != now:
                    yield from finish()
                    now, ids, held = int(block[x]), [], []
                ids.append(own[x:y].copy())
                held.extend(batch.column("v").slice(x, y - x).to_pylist())
        yield from finish()
        release()

    return rows.mapInArrow(to_blocks, _BLOCK)


class Search:
    """Many queries at once through one block after the other, with the k best of each so far.

    ``floor`` is a score that a query's results reach at least, where one is known.
    """

    def __init__(self, own: np.ndarray, q: np.ndarray, k: int, longest: float, floor: np.ndarray, home: np.ndarray):
        order = np.argsort(own, kind="stable")
        self.own, self.home, self.k, self.longest = own[order], home[order], k, longest
        self.q = np.ascontiguousarray(q[order], exact(longest))
        self.norm = (self.q.astype(np.float64) ** 2).sum(axis=1)
        self.least = floor[order].astype(np.float64)  # scores below it don't matter, nor do equal ones with an id from last_id on
        self.last_id = np.full(len(own), np.iinfo(np.int64).max)
        self.top = np.full((len(own), k), -np.inf)
        self.found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.computed, self.blocks, self.size = np.zeros(len(own), np.int64), np.zeros(len(own), np.int64), 0

    def reach(self, at: np.ndarray) -> np.ndarray:
        far = np.full(len(at), np.inf)
        some = np.isfinite(self.least[at])
        a = at[some]
        far[some] = np.sqrt(np.maximum(0.0, self.norm[a] + self.longest - 2 * self.least[a]) + 1e-7 * (1 + self.longest + self.norm[a])) + 1e-6
        return far

    def visit(self, block: int | None, dim: int, row: dict, first: bool) -> None:
        """``first`` takes the queries whose own block this is, otherwise all others."""
        nodes, routes = np.frombuffer(row["nodes"], _PAGE), np.frombuffer(row["routes"]).reshape(-1, dim + 1)
        ids, v = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["vectors"], narrow(self.longest)).reshape(-1, dim).astype(self.q.dtype)
        child: list[list[int]] = [[] for _ in nodes]
        for n, p in enumerate(nodes["parent"].tolist()):
            if p >= 0:
                child[p].append(n)
        square, mine = (routes * routes).sum(axis=1), np.flatnonzero((self.home == block) == first)

        def far(at: np.ndarray, pages: list[int]) -> np.ndarray:
            self.computed[at] += len(pages)
            return np.sqrt(np.maximum(0.0, self.norm[at][:, None] + square[pages] - 2 * self.q[at].astype(np.float64) @ routes[pages, :-1].T))

        def leaf(n: int, at: np.ndarray) -> None:
            x, size = int(nodes["start"][n]), int(nodes["size"][n])
            self.take(at, ids[x : x + size], v[x : x + size])

        def nearest(n: int, at: np.ndarray) -> None:
            if not child[n]:
                seen[at - at0] = n
                leaf(n, at)
                return
            own = far(at, child[n]).argmin(axis=1)
            for c in np.unique(own).tolist():
                nearest(child[n][c], at[own == c])

        def walk(n: int, at: np.ndarray, d: np.ndarray) -> None:
            if not child[n]:
                # entries lie between the page's inner and outer distance from its routing vector
                on = (nodes["inner"][n] - d <= self.reach(at)) & (seen[at - at0] != n)
                if on.any():
                    leaf(n, at if on.all() else at[on])
                return
            c = child[n]
            low = np.abs(d[:, None] - nodes["to_parent"][c]) - nodes["radius"][c]
            if not (low <= self.reach(at)[:, None]).any():
                return
            all_far = far(at, c)
            for j in np.argsort(all_far.mean(axis=0)).tolist():
                on = np.maximum(low[:, j], all_far[:, j] - nodes["radius"][c[j]]) <= self.reach(at)
                if on.all():
                    walk(c[j], at, all_far[:, j])
                elif on.any():
                    walk(c[j], at[on], all_far[on, j])

        for x in range(0, len(mine), SLICE_QUERIES):
            at = mine[x : x + SLICE_QUERIES]
            d = far(at, [0])[:, 0]
            on = d - nodes["radius"][0] <= self.reach(at)
            at, d = at[on], d[on]
            if not len(at):
                continue
            at0 = int(at[0])
            seen = np.full(int(at[-1]) - at0 + 1, -1)
            self.blocks[at] += 1
            if first:
                nearest(0, at)
            walk(0, at, d)

    def take(self, at: np.ndarray, ids: np.ndarray, v: np.ndarray) -> None:
        """Scores of some queries with the entries of one page."""
        self.computed[at] += len(ids)
        whole = len(at) == at[-1] - at[0] + 1
        score = (self.q[at[0] : at[-1] + 1] if whole else self.q[at]) @ v.T
        place = np.minimum(np.searchsorted(self.own[at], ids), len(at) - 1)
        self_rows = np.flatnonzero(self.own[at[place]] == ids)
        score[place[self_rows], self_rows] = -np.inf
        who, which = np.nonzero(score >= np.maximum(self.least[at], -1e30).astype(score.dtype)[:, None])
        if not len(who):
            return
        s, i = score[who, which].astype(np.float64), ids[which]
        good = (s > self.least[at[who]]) | (i < self.last_id[at[who]])
        who, s, i = who[good], s[good], i[good]
        if not len(who):
            return
        self.found.append((at[who], i, s))
        self.size += len(who)
        hit, slot = np.unique(who, return_inverse=True)
        place = np.arange(len(who)) - np.searchsorted(who, hit)[slot]  # ``who`` is in order
        more = np.full((len(hit), int(place.max()) + 1), -np.inf)
        more[slot, place] = s
        rows = at[hit]
        both = np.hstack([self.top[rows], more])
        self.top[rows] = both = np.partition(both, both.shape[1] - self.k, axis=1)[:, -self.k :]
        least = both.min(axis=1)
        risen = least > self.least[rows]
        self.least[rows[risen]] = least[risen]
        self.last_id[rows[risen]] = np.iinfo(np.int64).max
        if self.size > MOST_FOUND + 2 * self.k * len(self.own):
            self.trim()

    def trim(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Only the k best of every query stay, ties to the least id."""
        who, i, s = (np.concatenate([f[c] for f in self.found]) if self.found else np.empty(0, t) for c, t in enumerate((np.int64, np.int64, np.float64)))
        order = np.lexsort((i, -s, who))
        who, i, s = who[order], i[order], s[order]
        rank = np.arange(len(who)) - np.searchsorted(who, who)
        kth = rank == self.k - 1
        on = kth & (s >= self.least[who])
        self.last_id[who[on]] = i[on]
        good = rank < self.k
        who, i, s = who[good], i[good], s[good]
        self.found, self.size = [(who, i, s)], len(who)
        return who, i, s


def _chunked(asked: DataFrame, by: list[str]) -> DataFrame:
    """``dim, part, asked``: queries in lists of about CHUNK_ROWS, PART_QUERIES in a part at most (about)."""
    sizes = asked.groupBy(*by).agg(F.ceil(F.count("*") / CHUNK_ROWS).alias("chunks"))
    each = asked.join(sizes, by).withColumn("chunk", F.pmod(F.xxhash64("vec_id"), F.col("chunks")))
    lists = each.groupBy(*by, "chunk").agg(F.collect_list(F.struct("vec_id", "v", "bound", "own")).alias("asked"))
    return lists.withColumn("share", F.floor(F.col("chunk") / (PART_QUERIES // CHUNK_ROWS)).cast("long"))


class _Part:
    """The queries of one key, put together from lists."""

    def __init__(self) -> None:
        self.lists: list[pa.Array] = []

    def add(self, column: pa.ListArray, row: int) -> None:
        self.lists.append(column[row].values)

    def arrays(self, dim: int, longest: float) -> tuple[np.ndarray, ...]:
        of = lambda f: pa.concat_arrays([x.field(f) for x in self.lists])
        v = np.frombuffer(b"".join(of("v").to_pylist()), narrow(longest)).reshape(-1, dim)
        bound = of("bound").to_numpy(zero_copy_only=False).astype(np.float64)
        return of("vec_id").to_numpy(), v, np.where(np.isnan(bound), -np.inf, bound), of("own").to_numpy()


def _routed(lists: DataFrame, blocks: DataFrame, longest: dict[int, float]) -> DataFrame:
    """``dim, part, block``: for every part of the queries the blocks whose balls can serve one of them, not as its own."""
    roots = blocks.select(F.floor(F.col("block") / _DIM).cast("int").alias("dim"), "block", "route", "radius")
    n = roots.groupBy("dim").agg(F.ceil(F.count("*") / ROOT_ROWS).alias("groups"))
    roots = roots.join(n, "dim").withColumn("group", F.pmod(F.xxhash64("block"), F.col("groups")))
    parts = lists.select("dim", "part").distinct()
    none = F.lit(None)
    left = lists.join(n, "dim").select("dim", "part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("groups") - 1)).alias("group"), F.lit(0).alias("kind"), "asked", none.cast("long").alias("block"), none.cast("binary").alias("route"), none.cast("double").alias("radius"))
    right = roots.join(parts, "dim").select("dim", "part", "group", F.lit(1).alias("kind"), none.cast(lists.schema["asked"].dataType).alias("asked"), "block", "route", "radius")
    rows = left.unionByName(right).repartition("dim", "part", "group").sortWithinPartitions("dim", "part", "group", "kind")
    schema = pa.schema([("dim", pa.int32()), ("part", pa.int64()), ("block", pa.int64())])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held, search = None, _Part(), None
        for batch in batches:
            dims, parts, groups, kinds, block = (batch.column(c).to_pylist() for c in ("dim", "part", "group", "kind", "block"))
            wanted = []
            for row, now in enumerate(zip(dims, parts, groups, strict=True)):
                if now != key:
                    key, held, search = now, _Part(), None
                if kinds[row] == 0:
                    held.add(batch.column("asked"), row)
                    continue
                dim = dims[row]
                if search is None:
                    own, v, floor, home = held.arrays(dim, longest[dim])
                    search = Search(own, v, 1, longest[dim], floor, home)
                    reach, q = search.reach(np.arange(len(own))), search.q.astype(np.float64)
                r = np.frombuffer(batch.column("route")[row].as_py())
                far = np.sqrt(np.maximum(0.0, search.norm + r @ r - 2 * q @ r[:-1]))
                if ((far - batch.column("radius")[row].as_py() <= reach) & (search.home != block[row])).any():
                    wanted.append((dim, parts[row], block[row]))
            yield pa.RecordBatch.from_arrays([pa.array([w[c] for w in wanted], schema[c].type) for c in range(3)], schema=schema)
        release()

    return rows.mapInArrow(route, "dim int, part long, block long")


def _searched(blocks: DataFrame, lists: DataFrame, pairs: DataFrame, longest: dict[int, float], k: int, first: bool, tasks: int) -> DataFrame:
    """``query_id, vec_id, score``: every query's best in the blocks that ``pairs`` (dim, part, group, block) give its part.

    A row without ``vec_id`` has the distances computed, and the number of blocks. A
    task holds its queries, and one block at a time.
    """
    none = F.lit(None)
    some = ("nodes", "routes", "ids", "vectors")
    left = lists.join(pairs.select("dim", "part", "group").distinct(), ["dim", "part"]).select("dim", "part", "group", F.lit(0).alias("kind"), "asked", none.cast("long").alias("block"), *(none.cast("binary").alias(c) for c in some))
    right = blocks.join(pairs, "block").select("dim", "part", "group", F.lit(1).alias("kind"), none.cast(lists.schema["asked"].dataType).alias("asked"), "block", *some)
    rows = left.unionByName(right).repartition(tasks, "dim", "part", "group").sortWithinPartitions("dim", "part", "group", "kind")
    result = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()), ("blocks", pa.int64())])

    def told(search: Search | None) -> Iterator[pa.RecordBatch]:
        if search is None:
            return
        who, ids, score = search.trim()
        n = len(search.own)
        yield pa.RecordBatch.from_arrays([pa.array(search.own[who]), pa.array(ids), pa.array(score.astype(np.int64)), pa.nulls(len(who), pa.int64())], schema=result)
        yield pa.RecordBatch.from_arrays([pa.array(search.own), pa.nulls(n, pa.int64()), pa.array(search.computed), pa.array(search.blocks)], schema=result)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held, search = None, _Part(), None
        for batch in batches:
            dims, parts, groups, kinds, block = (batch.column(c).to_pylist() for c in ("dim", "part", "group", "kind", "block"))
            for row, now in enumerate(zip(dims, parts, groups, strict=True)):
                if now != key:
                    yield from told(search)
                    key, held, search = now, _Part(), None
                dim = dims[row]
                if kinds[row] == 0:
                    held.add(batch.column("asked"), row)
                    continue
                if search is None:
                    own, v, floor, home = held.arrays(dim, longest[dim])
                    search, held = Search(own, v, k, longest[dim], floor, home), _Part()
                search.visit(block[row], dim, {c: batch.column(c)[row].as_py() for c in some}, first)
        yield from told(search)
        release()

    return rows.mapInArrow(run, "query_id long, vec_id long, score long, blocks long")


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Batches of a few rows while tables are written whose rows are blocks: a batch is a few MB."""
    name, was = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set(name, str(BATCH_BLOCKS))
    try:
        yield
    finally:
        spark.conf.set(name, was)


def _answers(rows: DataFrame, queries: DataFrame, k: int, id_col: str, vector_col: str) -> tuple[DataFrame, Scratch]:
    spark = rows.sparkSession
    scratch = Scratch(spark, "metric-trees")
    data = scratch.keep(_vectors(rows, id_col, vector_col), "vectors")
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    asked = _vectors(queries, id_col, vector_col).groupBy("vec_id").agg(F.min_by(F.struct("dim", "v"), "v").alias("x")).select("vec_id", "x.dim", "x.v")
    asked = scratch.keep(asked, "asked-vectors")
    lengths = data.select("dim", square.alias("s"), F.lit(1).alias("n")).unionByName(asked.select("dim", square.alias("s"), F.lit(0).alias("n")))
    sizes = [r for r in lengths.groupBy("dim").agg(F.sum("n").alias("n"), F.max("s").alias("longest")).collect() if r.n]  # a row for each length of vectors
    longest = {r.dim: r.longest for r in sizes}
    pivots = _pivots(data, {r.dim: r.n for r in sizes}) if sizes else {}
    placed = scratch.keep(_placed(data, pivots, longest), "placed")
    scratch.drop("vectors")
    shares = placed.groupBy("dim", "pivot").agg(F.ceil(F.count("*") / BLOCK_ROWS).alias("shares"))  # MAX_PIVOTS rows for each length
    block = F.col("dim").cast("long") * _DIM + F.col("pivot") * _PIVOT
    dealt = placed.withColumn("_row", F.monotonically_increasing_id()).join(F.broadcast(shares), ["dim", "pivot"]).withColumn("block", block + F.pmod(F.xxhash64("_row"), F.col("shares")))
    blocks = scratch.keep(_blocks(dealt, longest), "blocks")
    asked = _placed(asked.where(F.col("dim").isin(list(longest))), pivots, longest).withColumn("own", block).withColumn("bound", F.lit(None).cast("long"))
    asked = scratch.keep(asked, "asked")
    # first pass: every query in its own block, a part for each block and PART_QUERIES of its queries
    lists = scratch.keep(_chunked(asked, ["dim", "own"]), "own-lists").select("dim", "own", "asked", (F.col("own") + F.col("share")).alias("part"))
    pairs = scratch.keep(lists.select("dim", "part", F.lit(0).cast("long").alias("group"), F.col("own").alias("block")).distinct(), "own-pairs")
    least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    with small_batches(spark):
        first = scratch.keep(_searched(blocks, lists.drop("own"), pairs, longest, k, True, max(least, min(MAX_TASKS, pairs.count()))), "own-results")
    bounds = first.where("vec_id is not null").groupBy("query_id").agg(F.sort_array(F.collect_list("score"), False).alias("s")).where(F.size("s") >= k).select(F.col("query_id").alias("vec_id"), F.element_at("s", k).alias("bound"))  # k scores of a query
    # second pass: parts of queries that lie near each other, against the blocks in reach of any
    n = asked.groupBy("dim", "pivot").agg(F.count("*").alias("n"))  # MAX_PIVOTS rows for each length
    before = F.sum("n").over(Window.partitionBy("dim").orderBy("pivot")) - F.col("n")
    regions = n.select("dim", "pivot", F.floor(before / PART_QUERIES).cast("long").alias("region"))
    bounded = asked.drop("bound").join(F.broadcast(regions), ["dim", "pivot"]).join(bounds, "vec_id", "left")
    lists = scratch.keep(_chunked(bounded, ["dim", "region"]), "lists").select("dim", "asked", (F.col("region") * 2**24 + F.col("share")).alias("part"))
    with small_batches(spark):
        routed = scratch.keep(_routed(lists, blocks, longest), "routed")
    n_pairs = routed.count()
    each = max(1, min(GROUP_BLOCKS, n_pairs // MIN_GROUPS))
    groups = routed.groupBy("dim", "part").agg(F.ceil(F.count("*") / each).alias("groups"))
    pairs = scratch.keep(routed.join(groups, ["dim", "part"]).withColumn("group", F.pmod(F.xxhash64("block"), F.col("groups"))).drop("groups"), "pairs")
    with small_batches(spark):
        rest = scratch.keep(_searched(blocks, lists, pairs, longest, k, False, max(least, min(MAX_TASKS, 2 * n_pairs // each))), "results")
    return first.unionByName(rest), scratch


def top_k(rows: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``query_id, rank, vec_id, score``: the k rows of the highest product for every query."""
    found, scratch = _answers(rows, queries, k, id_col, vector_col)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.where("vec_id is not null").withColumn("rank", F.row_number().over(best)).where(f"rank <= {k}")
    return scratch.last(ranked.select("query_id", "rank", "vec_id", "score"), "best")


def work(rows: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``query_id, computed, blocks``: distances that the search computes for every query, and blocks it goes to."""
    found, scratch = _answers(rows, queries, k, id_col, vector_col)
    return scratch.last(found.where("vec_id is null").groupBy("query_id").agg(F.sum("score").alias("computed"), F.sum("blocks").alias("blocks")), "work")
