"""Near-duplicate vectors through a robust-pruned flat graph.

Equal vectors form one class. Class vectors go to the ``overlap`` nearest of a set of
centroids, so shards overlap. Each shard builds a flat graph: nearest candidates,
thinned by the robust rule (a candidate goes when one already kept is nearer to it, by
``alpha``, than the vertex is). Adjacency lists of all shards are united by vertex. In
its home shard every vector is then searched for: greedily from the shard's medoid
with a beam, and from what lies within range the search keeps expanding until nothing
new is in range. Cosines of what it meets are verified in double precision.

Shards above ``most`` vectors are split again by centroids of their own, as long as
those lie apart: the centroids within a group whose pairs all reach ``least`` are so
close that only one of them stays, so no such group is cut. A shard that does not come
apart is a tight group, where a graph of bounded degree would be no help: each of its
home vectors is compared with the whole shard, pair of blocks by pair of blocks, at a
cost that grows with the group's square. One row per vector and shard or pair of blocks
leaves a search (a count and a local root), never pairs. The fit sample (``sample``
vectors) is the only thing that reaches the driver. ``recall`` audits the result
against brute force.

Defined results: a vector that is null, empty, zero, or holds a null or non-finite
component links with nothing; vectors link with those of their own length; repeated
rows of one vec_id count once; a row without vec_id is returned unlinked; an empty
table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import need, prepare, stored
from .components import components


_BLOCK_ROWS = 32_768  # of a tight group, in one side of a task


def _matrix(column) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    width = len(column[0]) if len(column) else 0
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), width).astype(np.float64)


def _unit(x: np.ndarray) -> np.ndarray:
    # Scaled first, so that squares of very large or small components stay finite.
    x = x / np.abs(x).max(1, keepdims=True) if len(x) else x
    return x / np.sqrt((x * x).sum(1, keepdims=True)) if len(x) else x


def _centroids(x: np.ndarray, k: int, seed: int) -> np.ndarray:
    """k-means centres."""
    rng = np.random.default_rng(seed)
    c = x[rng.permutation(len(x))[:k]]
    for _ in range(3):
        own = (x @ c.T).argmax(1)
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        size = np.sqrt((sums * sums).sum(1, keepdims=True))
        c = np.where(size > 0, sums / np.where(size > 0, size, 1), c)
    return c


def _spread(c: np.ndarray, apart: float) -> np.ndarray:
    """Of centres within cosine ``apart`` of one another only one stays."""
    close = np.triu(c @ c.T >= apart, 1)
    stay: list[int] = []
    for i in range(len(c)):
        if not close[stay, i].any():
            stay.append(i)
    return c[stay]


def _assigner(centroids: dict[int, tuple[int, np.ndarray]], overlap: int):
    """Rows (id, copies, vec, shard, home) to the nearest centroids of their shard; ``centroids``: shard -> (first new shard, matrix)."""

    def assign(batches):
        for batch in batches:
            shard = batch.column(3).to_numpy(zero_copy_only=False)
            home = np.array(batch.column(4).to_pylist(), bool)
            take, new, first = [], [], []
            for s in np.unique(shard):
                rows = np.flatnonzero(shard == s)
                if s not in centroids:
                    take.append(rows), new.append(shard[rows]), first.append(home[rows])
                    continue
                base, c = centroids[s]
                k = min(overlap, len(c))
                x = _unit(_matrix(batch.column(2).take(pa.array(rows))))
                near = np.argsort(-(x @ c.T), axis=1, kind="stable")[:, :k]
                take.append(np.repeat(rows, k)), new.append((near + base).ravel())
                first.append((np.arange(k)[None, :] == 0).repeat(len(rows), 0).ravel() & np.repeat(home[rows], k))
            if take:
                at = pa.array(np.concatenate(take))
                yield pa.RecordBatch.from_arrays([*(batch.column(k).take(at) for k in range(3)), pa.array(np.concatenate(new).astype(np.int64)), pa.array(np.concatenate(first))], names=["id", "copies", "vec", "shard", "home"])

    return assign


def graph(x: np.ndarray, degree: int, candidates: int, alpha: float) -> np.ndarray:
    """(n, degree) neighbours by place, -1 where there are fewer."""
    n = len(x)
    adj = np.full((n, degree), -1, np.int64)
    if n < 2:
        return adj
    s = (x @ x.T).astype(np.float32)
    np.fill_diagonal(s, -2)
    c = min(candidates, n - 1)
    near = np.argpartition(-s, c - 1, axis=1)[:, :c] if c < n - 1 else np.argsort(-s, axis=1)[:, :c]
    score = np.take_along_axis(s, near, 1)
    order = np.argsort(-score, axis=1, kind="stable")
    near, score = np.take_along_axis(near, order, 1), np.take_along_axis(score, order, 1)
    alive = np.ones((n, c), bool)
    every = np.arange(n)
    for r in range(min(degree, c)):
        pick = alive.argmax(1)
        there = alive[every, pick]
        if not there.any():
            break
        best = near[every, pick]
        adj[there, r] = best[there]
        # Squared distance of unit vectors is 2 - 2 cos.
        between = 2 - 2 * s[best[:, None], near]
        alive &= ~((alpha * between <= 2 - 2 * score) & there[:, None])
        alive[every, pick] = False
    return adj


def range_search(x: np.ndarray, adj: np.ndarray, queries: np.ndarray, least: float, beam: int) -> list[np.ndarray]:
    """Places within ``least`` cosine of each query place, by greedy search from the medoid and expansion."""
    n = len(x)
    medoid = int((x @ x.sum(0)).argmax())
    width = min(beam, n)
    found = []
    for low in range(0, len(queries), 512):
        q = queries[low : low + 512]
        ids = np.full((len(q), width), -1, np.int64)
        score = np.full((len(q), width), -9.0)
        done = np.ones((len(q), width), bool)
        ids[:, 0], score[:, 0], done[:, 0] = medoid, x[q] @ x[medoid], False
        for _ in range(4 * beam):
            open_ = np.where(done, -9.0, score)
            pick = open_.argmax(1)
            rows = np.flatnonzero(open_[np.arange(len(q)), pick] > -9)
            if not len(rows):
                break
            done[rows, pick[rows]] = True
            next_ = adj[ids[rows, pick[rows]]]
            got = np.einsum("rkd,rd->rk", x[next_], x[q[rows]])
            got[next_ < 0] = -9
            got[(next_[:, :, None] == ids[rows][:, None, :]).any(2)] = -9
            all_id, all_score = np.concatenate([ids[rows], next_], 1), np.concatenate([score[rows], got], 1)
            all_done = np.concatenate([done[rows], got <= -9], 1)
            top = np.argsort(-all_score, axis=1, kind="stable")[:, :width]
            ids[rows], score[rows], done[rows] = (np.take_along_axis(a, top, 1) for a in (all_id, all_score, all_done))
        for k, at in enumerate(q):
            seen = np.zeros(n, bool)
            front = np.unique(np.append(ids[k][score[k] >= least], at))
            seen[front] = True
            hits = [front]
            while len(front):
                new = np.unique(adj[front])
                new = new[new >= 0]
                new = new[~seen[new]]
                seen[new] = True
                front = new[x[new] @ x[at] >= least]
                hits.append(front)
            every = np.concatenate(hits)
            found.append(every[every != at])
    return found


def _roots(n: int, links: list[tuple[int, np.ndarray]], ids: np.ndarray) -> np.ndarray:
    top = np.arange(n)

    def find(a: int) -> int:
        while top[a] != a:
            top[a] = top[top[a]]
            a = top[a]
        return a

    for a, others in links:
        for b in others:
            x, y = find(a), find(int(b))
            if x != y:
                x, y = (x, y) if ids[x] < ids[y] else (y, x)
                top[y] = x
    return np.array([ids[find(a)] for a in range(n)], np.int64)


def near_vectors(vectors: DataFrame, least: float = 0.95, overlap: int = 4, shard_size: int = 1000, most: int = 6000, sample: int = 4096, degree: int = 32, candidates: int = 96, alpha: float = 1.2, beam: int = 12, seed: int = 3) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row of ``vectors`` (vec_id, embedding)."""
    need(vectors, "vec_id", "embedding")
    spark = vectors.sparkSession
    prepare(spark)
    vec = F.col("embedding").cast("array<double>")
    good = F.coalesce((F.size(vec) > 0) & F.forall(vec, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists(vec, lambda v: v != 0), F.lit(False))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.when(good, F.transform(vec, lambda v: v + 0.0)).alias("vec"))
    # In parts, not as an array: the hash of a class, and then the class itself.
    usable = rows.where("vec is not null and vec_id is not null").distinct()
    classes = stored(usable.groupBy("vec").agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("copies")).select("id", "copies", "vec", F.size("vec").alias("width")), "classes")
    # A shard for each length first: only vectors of one length ever meet.
    whole = classes.select("id", "copies", "vec", (-F.col("width").cast("long")).alias("shard"), F.lit(True).alias("home"))
    found = stored(_searched(whole, least, overlap, shard_size, most, sample, degree, candidates, alpha, beam, seed), "found")
    counts = found.groupBy("id").agg(F.sum("links").alias("links"))
    joined = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")).distinct())
    of_class = classes.join(counts, "id", "left").join(joined, "id", "left").select("vec", F.col("copies"), F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "id").alias("component"))
    placed = rows.join(of_class, "vec", "left")
    linked = F.col("vec_id").isNotNull() & F.col("component").isNotNull()
    component = F.when(linked, F.col("component")).otherwise(F.col("vec_id"))
    return placed.select("vec_id", F.when(linked, F.col("links") + F.col("copies") - 1).otherwise(F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def _searched(rows: DataFrame, least, overlap, shard_size, most, sample, degree, candidates, alpha, beam, seed) -> DataFrame:
    """(id, links, root) of class vectors; links count the copies of other classes and add up by id."""
    schema = "id long, copies long, vec array<double>, shard long, home boolean"
    next_shard = 1
    parent: dict[int, int] = {}
    tight: dict[int, int] = {}
    for again in (*[True] * 8, False):
        large = {r.shard: r["count"] for r in rows.groupBy("shard").count().where(F.col("count") > most).collect() if r.shard not in tight}
        fresh: dict[int, tuple[int, np.ndarray]] = {}
        for shard, count in large.items():
            if not again or 2 * count > parent.get(shard, 2 * count):
                tight[shard] = count
                continue
            few = rows.where(F.col("shard") == shard).orderBy(F.xxhash64("id", F.lit(seed))).limit(sample).select("vec").toArrow()
            k = max(2, min(1024, sample // 2, count * overlap // shard_size))
            every = _centroids(_unit(_matrix(few.column(0))), k, seed)
            centres = _spread(every, min(0.9, least))
            if len(centres) <= overlap:
                centres = _spread(every, least)
            if len(centres) <= overlap:
                tight[shard] = count
                continue
            fresh[shard] = (next_shard, centres)
            parent.update((next_shard + i, count) for i in range(len(centres)))
            next_shard += len(centres)
        if not fresh:
            break
        rows = stored(rows.mapInArrow(_assigner(fresh, overlap), schema), "shards")
    if not tight:
        return _by_graph(rows, least, degree, candidates, alpha, beam)
    dense = F.col("shard").isin(list(tight))
    return _by_graph(rows.where(~dense), least, degree, candidates, alpha, beam).unionByName(_by_blocks(rows.where(dense), tight, least, most, seed))


def _merge(top: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Roots by place once ``a`` and ``b`` are linked, all pointing at the first place of their component."""
    while True:
        x, y = top[a], top[b]
        if (x == y).all():
            return top
        np.minimum.at(top, np.maximum(x, y), np.minimum(x, y))
        while (top[top] != top).any():
            top = top[top]


def _by_blocks(rows: DataFrame, tight: dict[int, int], least: float, most: int, seed: int) -> DataFrame:
    """(id, links, root): home vectors against all vectors of their shard, one task a pair of blocks.

    A shard has up to 8 blocks of about ``most`` vectors, and more only once a block would exceed _BLOCK_ROWS.
    """
    blocks = {s: max(min(8, -(-n // most)), -(-n // _BLOCK_ROWS)) for s, n in tight.items()}
    sizes = rows.sparkSession.createDataFrame([(s, m) for s, m in blocks.items()], "shard long, m int")
    placed = rows.join(F.broadcast(sizes), "shard").withColumn("block", F.pmod(F.xxhash64("id", F.lit(seed)), F.col("m")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("other")
    pairs = placed.select("shard", "block", "id", "copies", "vec", "home", other).withColumns({"i": F.least("block", "other"), "j": F.greatest("block", "other")}).drop("other")

    def count(table):
        table = table.sort_by("id")
        ids, copies = table.column("id").to_numpy(), table.column("copies").to_numpy().astype(np.float64)
        home, block = np.array(table.column("home").to_pylist(), bool), table.column("block").to_numpy()
        x = _unit(_matrix(table.column("vec")))
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        left, right = np.flatnonzero(block == i), np.flatnonzero(block == j)
        xr, cr = x[right], copies[right]
        links, top = np.zeros(len(ids)), np.arange(len(ids), dtype=np.int32)
        step = max(1, (1 << 21) // max(1, len(right)))
        for low in range(0, len(left), step):
            part = left[low : low + step]
            hit = x[part] @ xr.T >= least
            if i == j:
                hit[np.arange(len(part)), np.arange(low, low + len(part))] = False
            weight = hit.astype(np.float64)
            links[part] += weight @ cr
            if i != j:
                links[right] += copies[part] @ weight
            # Only links between what is still apart.
            a, b = np.nonzero(hit & (top[part][:, None] != top[right][None, :]))
            if len(a):
                top = _merge(top, part[a], right[b])
        return pa.Table.from_arrays([pa.array(ids), pa.array(links.astype(np.int64), mask=~home), pa.array(ids[top])], names=["id", "links", "root"])

    return pairs.groupBy("shard", "i", "j").applyInArrow(count, "id long, links long, root long")


def _by_graph(rows: DataFrame, least, degree, candidates, alpha, beam) -> DataFrame:
    """(id, links, root): home vectors by a search of their shard's graph."""

    def build(table):
        ids = table.column("id").to_numpy()
        adj = graph(_unit(_matrix(table.column("vec"))), degree, candidates, alpha)
        lists = [ids[a[a >= 0]].tolist() for a in adj]
        return pa.Table.from_arrays([pa.array(ids), pa.array(lists, pa.list_(pa.int64()))], names=["id", "near"])

    edges = rows.groupBy("shard").applyInArrow(build, "id long, near array<long>")
    united = edges.groupBy("id").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near"))
    ready = rows.join(united, "id").select("shard", "id", "copies", "vec", "home", "near")

    def search(table):
        ids, copies = table.column("id").to_numpy(), table.column("copies").to_numpy()
        x = _unit(_matrix(table.column("vec")))
        order = np.argsort(ids)
        near = table.column("near").combine_chunks()
        flat, owner = near.flatten().to_numpy(), np.repeat(np.arange(len(ids)), np.diff(near.offsets.to_numpy()))
        place = np.minimum(np.searchsorted(ids[order], flat), len(ids) - 1)
        here = ids[order][place] == flat
        owner, to = owner[here], order[place[here]]
        # Links run both ways, so that a vertex can be reached from those that it chose.
        owner, to = np.concatenate([owner, to]), np.concatenate([to, owner])
        both = np.unique(owner * len(ids) + to)
        owner, to = both // len(ids), both % len(ids)
        count = np.bincount(owner, minlength=len(ids))
        adj = np.full((len(ids), max(1, count.max() if len(count) else 1)), -1, np.int64)
        adj[owner, np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)] = to
        home = np.flatnonzero(np.array(table.column("home").to_pylist(), bool))
        found = range_search(x, adj, home, least, beam)
        links = np.full(len(ids), -1, np.int64)
        links[home] = [int(copies[f].sum()) for f in found]
        roots = _roots(len(ids), list(zip(home.tolist(), found)), ids)
        return pa.Table.from_arrays([pa.array(ids), pa.array(links, mask=links < 0), pa.array(roots)], names=["id", "links", "root"])

    return ready.groupBy("shard").applyInArrow(search, "id long, links long, root long")


def recall(vectors: DataFrame, found: DataFrame, least: float = 0.95, every: int = 100) -> DataFrame:
    """(n_true, n_found, recall): links of rows whose vec_id is divisible by ``every``, against all rows by brute force.

    The queries meet the table in sets of about 20,000.
    """
    every_asked = vectors.where((F.col("vec_id") % every == 0) & F.col("embedding").isNotNull()).select("vec_id", "embedding")
    sets = max(1, -(-every_asked.count() // 20_000))

    def hits_of(asked) -> DataFrame:
        ids, q = asked.column(0).to_numpy(), _unit(_matrix(asked.column(1))) if asked.num_rows else np.zeros((0, 1))

        def count(batches):
            for batch in batches:
                if batch.num_rows and len(ids):
                    hits = (_unit(_matrix(batch.column(1))) @ q.T >= least) & (batch.column(0).to_numpy(zero_copy_only=False)[:, None] != ids[None, :])
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(hits.sum(0).astype(np.int64))], names=["vec_id", "n"])

        return vectors.select("vec_id", "embedding").where("embedding is not null").mapInArrow(count, "vec_id long, n long").groupBy("vec_id").agg(F.sum("n").alias("n"))

    true = stored(hits_of(every_asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(sets)) == 0).toArrow()), "true")
    for k in range(1, sets):
        true = true.unionByName(stored(hits_of(every_asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(sets)) == k).toArrow()), "true"))
    both = true.join(found.select("vec_id", "n_links"), "vec_id")
    return both.agg(F.sum("n").alias("n_true"), F.sum(F.least("n", "n_links")).alias("n_found")).select("n_true", "n_found", (F.col("n_found") / F.nullif("n_true", F.lit(0))).alias("recall"))
