"""Near-duplicate groups by fast similarity sketching, banding and exact checks.

Sketch: in round i every shingle is thrown into one of t bins with a hash of round i;
a bin keeps the least (round, hash). Rounds go on until no bin is empty; from round t
on, round t+b fills bin b from all shingles, so every coordinate is filled. Bands of
``rows`` coordinates give bucket keys. With 48 bands of 7 rows a pair at similarity
0.8 shares no bucket with a chance of 1e-5.

Texts with equal shingle sets are one class from the start. In every bucket the class
that meets most others over all its buckets is the hub; each class is first checked
against the hub it shares most buckets with. What these links join is contracted.
Components that still meet in a bucket are then compared block against block, so a
class is never left out because of the hub it got: either in the cluster of all buckets
that hang together, each row once with every block, or, where chains of buckets make a
cluster so large that this would move more rows, bucket by bucket. Every link is
confirmed on the full shingle sets.

Defined cases: a null or empty text, or one without words, has no shingles and links
with nothing. Repeated rows give repeated result rows. Rows that share a ``doc_id``
are versions of one document, linked where any version is. A null id stays alone with
a null component and is kept. Other columns of the input don't matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, arrow_rows, hot_floor, met, release
from .components import components, forest_components

BANDS, ROWS = 48, 7
#: A block of rows that one task compares with another block: rows, and shingles.
BLOCK_ROWS, BLOCK_SHINGLES = 400, 2_000_000
#: Rows moved for buckets count so much against rows moved for clusters.
BUCKET_WEIGHT = 1.0
_EMPTY = np.uint64(2**64 - 1)
_STEP, _MULT, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93), np.uint64(0xFF51AFD7ED558CCD)
_VALUE_BITS = np.uint64(50)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    x = (x ^ (x >> np.uint64(32))) * _MULT
    x = (x ^ (x >> np.uint64(29))) * _MIX
    return x ^ (x >> np.uint64(32))


def shingle_set(text: str | None, k: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of k-word shingles; fewer words are one shingle."""
    from xxhash import xxh3_64_intdigest

    words = (text or "").encode().lower().split()
    n = len(words)
    if n == 0:
        return np.empty(0, np.uint64)
    if n < k:
        return np.array([xxh3_64_intdigest(b" ".join(words), seed=n)], np.uint64)
    w = np.fromiter(map(xxh3_64_intdigest, words), np.uint64, n)
    h = w[: n - k + 1].copy()
    for j in range(1, k):
        h = h * _STEP + w[j : n - k + 1 + j]
    return np.unique(mix(h))


def sketch(x: np.ndarray, doc: np.ndarray, n_docs: int, t: int) -> np.ndarray:
    """Sketches of t coordinates of the documents whose shingles are x[doc == i]; each has one at least."""
    s = np.full(n_docs * t, _EMPTY)
    base, seeds = doc.astype(np.int64) * t, mix(np.arange(1, 2 * t + 1, dtype=np.uint64) * _STEP)
    low = (np.uint64(1) << _VALUE_BITS) - np.uint64(1)
    for i in range(t):
        h = mix(x ^ seeds[i])
        place = ((h >> np.uint64(44)) * np.uint64(t) >> np.uint64(20)).astype(np.int64)
        np.minimum.at(s, base + place, (np.uint64(i) << _VALUE_BITS) | (mix(h + _STEP) & low))
        open_docs = (s.reshape(n_docs, t) == _EMPTY).any(axis=1)
        if not open_docs.any():
            return s.reshape(n_docs, t)
        if (keep := open_docs[base // t]).mean() < 0.9:
            x, base = x[keep], base[keep]
    out = s.reshape(n_docs, t)
    for b in np.flatnonzero((out == _EMPTY).any(axis=0)):
        value = (np.uint64(t + b) << _VALUE_BITS) | (mix(x ^ seeds[t + b]) & low)
        np.minimum.at(s, base + b, value)
    return out


def band_keys(s: np.ndarray, bands: int, rows: int) -> np.ndarray:
    h = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * _MIX, (len(s), bands)).copy()
    cut = s.reshape(len(s), bands, rows)
    for r in range(rows):
        h = mix(h * _STEP + cut[:, :, r])
    return h.view(np.int64)


def signatures(docs: DataFrame, k: int, bands: int, rows: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n, fp, bands`` per row; fp (of the whole set) and bands are null without shingles."""
    from xxhash import xxh3_128_digest

    schema = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("fp", pa.binary()), ("bands", pa.list_(pa.int64()))])

    def each(cols: dict[str, list]) -> dict[str, list]:
        sets = [shingle_set(t, k) for t in cols["text"]]
        full = [i for i, s in enumerate(sets) if len(s)]
        keys: list = [None] * len(sets)
        if full:
            sizes = [len(sets[i]) for i in full]
            s = sketch(np.concatenate([sets[i] for i in full]), np.repeat(np.arange(len(full)), sizes), len(full), bands * rows)
            for i, row in zip(full, band_keys(s, bands, rows), strict=True):
                keys[i] = row
        return {"doc_id": cols["doc_id"], "n": [len(s) for s in sets], "fp": [xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets], "bands": keys}

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return src.mapInArrow(arrow_rows(each, schema, 256), "doc_id long, n long, fp binary, bands array<long>")


def verified(texts: DataFrame, pairs: DataFrame, k: int, percent: int, scratch: Scratch) -> DataFrame:
    """Those ``pairs`` (u, v) with 100 * intersection >= percent * union of the full sets.

    Every u is a hub. Its partners are dealt out in ranges of (u, v), so a hub with many
    spans several parts; its set goes to each of them once.
    """
    dealt = scratch.keep(pairs.repartitionByRange("u", "v").withColumn("part", F.spark_partition_id()), "dealt")
    members = dealt.select(F.col("v").alias("doc_id"), "u", "part", F.lit(1).alias("member"))
    hubs = dealt.select("u", "part").distinct().select(F.col("u").alias("doc_id"), "u", "part", F.lit(0).alias("member"))
    roles = members.unionByName(hubs)
    sets_schema = pa.schema([("doc_id", pa.int64()), ("u", pa.int64()), ("part", pa.int32()), ("member", pa.int32()), ("shingles", pa.binary())])

    def to_sets(cols: dict[str, list]) -> dict[str, list]:
        return {c: cols[c] for c in ("doc_id", "u", "part", "member")} | {"shingles": [shingle_set(t, k).tobytes() for t in cols["text"]]}

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, hub_sets = None, []
        for batch in batches:
            us, vs = [], []
            for doc, u, part, member, raw in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "u", "part", "member", "shingles")), strict=True):
                own = np.frombuffer(raw, np.uint64)
                if (u, part) != group:
                    group, hub_sets = (u, part), []
                if not member:
                    hub_sets.append(own)
                    continue
                for hub in hub_sets:
                    if 100 * min(len(hub), len(own)) < percent * max(len(hub), len(own)):
                        continue
                    both = len(np.intersect1d(hub, own, assume_unique=True))
                    if 100 * both >= percent * (len(hub) + len(own) - both):
                        us.append(u)
                        vs.append(doc)
                        break
            yield pa.RecordBatch.from_pydict({"u": pa.array(us, pa.int64()), "v": pa.array(vs, pa.int64())})
        release()

    sets = texts.join(roles.hint("shuffle_hash"), "doc_id").mapInArrow(arrow_rows(to_sets, sets_schema, 128), "doc_id long, u long, part int, member int, shingles binary")
    return sets.repartition("u", "part").sortWithinPartitions("u", "part", "member").mapInArrow(compare, "u long, v long")


def spanning_links(sets: list[np.ndarray], side: np.ndarray, comp: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links between rows of side 0 and side 1 that join different components, as a forest.

    All intersections come from products of incidence matrices, some thousand
    shingles at a time; a shingle that only one row has can't count.
    """
    size = np.array([len(s) for s in sets], np.int64)
    _, col, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(sets)), size)
    kept = count[col] > 1
    row, col = row[kept], (np.cumsum(count > 1) - 1)[col[kept]]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    place = np.zeros(len(sets), np.int64)
    rows = [np.flatnonzero(side == k) for k in (0, 1)]
    for r in rows:
        place[r] = np.arange(len(r))
    both = np.zeros((len(rows[0]), len(rows[1])), np.float32)
    for first in range(0, int(col[-1]) + 1 if len(col) else 0, 4096):
        cut = slice(*np.searchsorted(col, [first, first + 4096]))
        grid = []
        for k, r in enumerate(rows):
            own = side[row[cut]] == k
            g = np.zeros((len(r), 4096), np.float32)
            g[place[row[cut][own]], col[cut][own] - first] = 1
            grid.append(g)
        both += grid[0] @ grid[1].T
    a, b = rows
    linked = (100 * both >= percent * (size[a][:, None] + size[b][None, :] - both)) & (comp[a][:, None] != comp[b][None, :])
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    out = []
    i, j = np.nonzero(linked)
    for x, y in zip(a[i].tolist(), b[j].tolist(), strict=True):
        p, q = root(int(comp[x])), root(int(comp[y]))
        if p != q:
            parent[max(p, q)] = min(p, q)
            out.append((x, y))
    return out


def _mixed(members: DataFrame, comp: DataFrame, floor: int, scratch: Scratch) -> DataFrame:
    """``key, doc_id, n, component, least`` of buckets that hold several components."""
    placed = members.join(comp.select(F.col("node").alias("doc_id"), "component"), "doc_id", "left").select("key", "doc_id", "n", F.coalesce("component", "doc_id").alias("component"))
    placed = scratch.keep(placed, "in-components")
    several = placed.groupBy("key").agg(F.min("component").alias("least"), F.max("component").alias("b"), F.count("*").alias("c")).where("least <> b").select("key", "least", "c")
    return met(placed, scratch.keep(several, "several"), ["key"], F.col("c") > floor).drop("c")


def _blocks(rows: DataFrame, group: str) -> DataFrame:
    """``group, c, major, k, l, moved``: a group's rows, its largest component, blocks outside and inside of that, and copies to move.

    The rows outside a group's largest component meet all blocks, the others only theirs.
    """
    parts = rows.groupBy(group, "component").agg(F.count("*").alias("c"), F.max("n").alias("n"))
    whole = parts.groupBy(group).agg(F.max(F.struct("c", "component")).alias("major"), F.sum("c").alias("c"), F.max("n").alias("n"))
    block = F.greatest(F.lit(8), F.least(F.lit(BLOCK_ROWS), F.floor(BLOCK_SHINGLES / F.col("n"))))
    minors = F.col("c") - F.col("major.c")
    sized = whole.select(group, "c", "major", F.ceil(minors / block).cast("int").alias("k"), F.ceil(F.col("major.c") / block).cast("int").alias("l"))
    return sized.select(group, "c", F.col("major.component").alias("major"), "k", "l", (minors * (F.col("k") + F.col("l")) + F.col("major.c") * F.col("k")).alias("moved"))


def _dealt(rows: DataFrame, blocks: DataFrame, group: str, kind: int, floor: int) -> DataFrame:
    """Rows of groups with their own block and the number of blocks that they meet."""
    minor = F.col("component") != F.col("major")
    own = F.when(minor, F.pmod(F.xxhash64("doc_id"), F.col("k"))).otherwise(F.col("k") + F.pmod(F.xxhash64("doc_id"), F.col("l"))).cast("int")
    placed = met(rows, blocks, [group], F.col("c") > floor).withColumn("own", own)
    return placed.select("doc_id", "component", F.lit(kind).alias("kind"), F.col(group).alias("g"), "own", F.when(minor, F.col("k") + F.col("l")).otherwise(F.col("k")).alias("n_tasks"))


def _rest_links(texts: DataFrame, mixed: DataFrame, scratch: Scratch, k: int, percent: int) -> DataFrame:
    """Links between components that meet in buckets, none left out.

    A cluster holds the components that hang together by buckets. Its rows are compared
    in the cluster or in its buckets, whichever moves fewer rows; buckets with the same
    rows count as one. A task holds two blocks of bounded size and returns a forest.
    """
    floor = hot_floor(mixed.count())
    cluster = components(mixed.select(F.col("component").alias("u"), F.col("least").alias("v")), scratch, "clusters").withColumnRenamed("component", "cluster")
    cluster = scratch.keep(cluster.withColumnRenamed("node", "component"), "cluster-of")
    rows = scratch.keep(mixed.groupBy("doc_id").agg(F.max("n").alias("n"), F.max("component").alias("component")).join(cluster, "component"), "cluster-rows")
    clusters = scratch.keep(_blocks(rows, "cluster"), "cluster-blocks")
    # buckets by their sizes alone; rows are dealt by bucket only where that moves less
    sign = mixed.groupBy("key").agg(F.min("least").alias("component"), F.count("*").alias("size"), F.bit_xor(F.xxhash64("doc_id")).alias("x"), F.bit_xor(F.xxhash64("doc_id", F.lit(1))).alias("y"))
    once = sign.groupBy("size", "x", "y").agg(F.min(F.struct("key", "component")).alias("b")).select("b.key", "b.component")
    buckets = scratch.keep(_blocks(mixed, "key").join(once, "key").join(cluster, "component"), "buckets")
    less = buckets.groupBy("cluster").agg((F.sum("moved") * BUCKET_WEIGHT).alias("by_bucket")).join(clusters.select("cluster", "moved"), "cluster").where("by_bucket < moved").select("cluster")
    less = scratch.keep(less, "by-bucket")
    placed = _dealt(rows.join(less, "cluster", "left_anti"), clusters, "cluster", 0, floor)
    if not less.isEmpty():
        few = scratch.keep(buckets.join(less, "cluster").drop("cluster", "component"), "some-buckets")
        placed = placed.unionByName(_dealt(mixed.select("key", "doc_id", "n", "component"), few, "key", 1, floor))
    placed = scratch.keep(placed, "placed")
    schema = pa.schema([("doc_id", pa.int64()), ("component", pa.int64()), ("kind", pa.int32()), ("g", pa.int64()), ("own", pa.int32()), ("n_tasks", pa.int32()), ("shingles", pa.binary())])

    def to_sets(cols: dict[str, list]) -> dict[str, list]:
        return {c: cols[c] for c in ("doc_id", "component", "kind", "g", "own", "n_tasks")} | {"shingles": [shingle_set(t, k).tobytes() for t in cols["text"]]}

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, held = None, []

        def finish() -> pa.RecordBatch:
            found = []
            if held and group is not None:
                i, j = group[2:]
                # in a block of its own every row stands on either side
                rows = [(h, 0) for h in held if h[1] == i] + [(h, 1) for h in held if h[1] == j]
                ids = [h[0] for h, _ in rows]
                found = [(ids[x], ids[y]) for x, y in spanning_links([h[3] for h, _ in rows], np.array([s for _, s in rows]), np.array([h[2] for h, _ in rows], np.int64), percent)]
            return pa.RecordBatch.from_pydict({"u": pa.array([x for x, _ in found], pa.int64()), "v": pa.array([y for _, y in found], pa.int64())})

        for batch in batches:
            for kind, g, i, j, doc, own, comp, raw in zip(*(batch.column(c).to_pylist() for c in ("kind", "g", "i", "j", "doc_id", "own", "component", "shingles")), strict=True):
                if (kind, g, i, j) != group:
                    if held:
                        yield finish()
                    group, held = (kind, g, i, j), []
                held.append((doc, own, comp, np.frombuffer(raw, np.uint64)))
        yield finish()
        release()

    sets = texts.join(placed.hint("shuffle_hash"), "doc_id").mapInArrow(arrow_rows(to_sets, schema, 128), "doc_id long, component long, kind int, g long, own int, n_tasks int, shingles binary")
    tasks = sets.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n_tasks") - 1))).withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other")).drop("n_tasks", "other")
    return tasks.repartition("kind", "g", "i", "j").sortWithinPartitions("kind", "g", "i", "j").mapInArrow(compare, "u long, v long")


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` for every row; links are at ``percent`` or more."""
    spark: SparkSession = docs.sparkSession
    scratch = Scratch(spark, "near-duplicates")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    marks = scratch.keep(signatures(docs, k, bands, rows, id_col, text_col), "marks")
    classes = scratch.keep(marks.where("doc_id is not null and fp is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")), "classes")
    heads = marks.join(classes.select("fp", F.col("rep").alias("doc_id")), ["fp", "doc_id"], "left_semi")
    keyed = scratch.keep(heads.select("doc_id", "n", F.explode("bands").alias("key")), "keyed")
    shared = keyed.groupBy("key").agg(F.count("*").alias("c")).where("c > 1")
    floor = hot_floor(keyed.count())
    members = scratch.keep(met(keyed, scratch.keep(shared, "shared"), ["key"], F.col("c") > floor), "members")
    scratch.drop("keyed", "shared")
    reach = members.groupBy("doc_id").agg(F.sum("c").alias("reach"))
    ranked = scratch.keep(members.join(reach, "doc_id").select("key", "doc_id", "n", F.struct("reach", (-F.col("doc_id")).alias("minus"), F.col("n").alias("n")).alias("place")), "ranked")
    hubs = scratch.keep(ranked.groupBy("key").agg(F.max("place").alias("hub"), F.count("*").alias("c")), "hubs")
    starred = met(ranked, hubs, ["key"], F.col("c") > floor).where("hub.minus <> -doc_id").groupBy("doc_id", "n", "hub").agg(F.count("*").alias("c"))
    starred = starred.where(f"100 * least(n, hub.n) >= {percent} * greatest(n, hub.n)")
    best = starred.groupBy("doc_id").agg(F.max(F.struct("c", "hub")).alias("b")).select((-F.col("b.hub.minus")).alias("u"), F.col("doc_id").alias("v"))
    links = scratch.keep(verified(texts, scratch.keep(best, "best"), k, percent, scratch), "links")
    # a hub meets more others than its members, so links to hubs form a forest
    comp = forest_components(links, scratch, "first")
    mixed = scratch.keep(_mixed(members, comp, floor, scratch), "mixed")
    if not mixed.isEmpty():
        more = scratch.keep(_rest_links(texts, mixed, scratch, k, percent), "more")
        if not more.isEmpty():
            comp = components(links.unionByName(more), scratch, "second")
    comp = scratch.keep(comp, "components")
    labelled = classes.join(comp.withColumnRenamed("node", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    done = marks.where("fp is not null").select("doc_id", "n", "fp").join(labelled, "fp", "left").select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))
    bare = marks.where("fp is null").select("doc_id", "n", F.col("doc_id").alias("component_id"))
    every = done.unionByName(bare).select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))
    return scratch.last(every, "result")


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one row of every near-duplicate group, the one with the least id.

    Rows without shingles or without an id stay. A row that repeats the id of another
    goes too, whichever of the two it is.
    """
    found = near_duplicates(docs, k, percent)
    gone = found.where("not kept").select("doc_id").distinct()
    left = docs.join(gone.hint("shuffle_hash"), "doc_id", "left_anti").select(docs.columns)
    again = found.where("kept and doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    if again.isEmpty():
        return left
    once = left.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(docs.columns)
    return left.join(again, "doc_id", "left_anti").select(docs.columns).unionByName(once)
