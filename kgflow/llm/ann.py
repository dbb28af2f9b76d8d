"""Approximate nearest neighbours by largest inner product: one HNSW graph per shard.

Equal vectors form one class, so that a vector a third of all rows share is one node; a class
keeps its k + 1 least ids, which is all that any query's k nearest can need. Classes are dealt
to shards by a hash of the vector. A shard's graph is one row of flat arrays: vectors, ids, and
per level the nodes and their neighbours, -1 padded. Every query searches every shard and
results merge by score.

Inner product is reduced to distance by one more coordinate that gives all stored vectors of a shard one
length. Shards hold vectors of one magnitude (their lengths differ by less than a factor of 2) and are
scaled to it, so that coordinate is never large beside the others, a long vector distorts no other's
neighbourhood, and nothing overflows. The upper levels hold a sixteenth of the level below; the lowest
level is built by inserting batches that double, each found by searching the graph so far, with diverse
neighbours kept. Batches of queries walk the graph together.

Recall is measured as the graphs are built: a fixed number of queries is answered in every shard by all inner
products and by walks that double in width, and a magnitude takes the least width at which its graphs find
``RECALL`` of what is among these queries' k nearest over all shards. Where that is too little to judge by, or no
width reaches it, each shard and block of queries measures its own k nearest in the same way, and a shard where
the walk would visit most nodes is searched by all inner products.

Edge cases: vectors that are null, zero, or hold null or non-finite components take no part, nor
do rows with a null id; vectors of different length are never compared; with fewer candidates
than k all are returned; ties go to the smaller id; rows with one id and different vectors are all searched,
and a query's result names an id once, with its best score; columns beside id and vector are ignored,
names match in any case.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgflow.llm.frames import by_position, column
from kgflow.session import settled, width

LINKS, EF_BUILD, EF_SEARCH = 16, 64, 96
#: Vectors of a shard at most; shards of a magnitude at least, so that small tables use several cores, if they have as many vectors.
SHARD, LEAST_SHARDS, LEAST = 65536, 12, 256
#: Partitions at most in which shards are built.
MOST_PARTS = 1 << 15
#: Bytes of the queries that meet a shard together.
QUERY_BYTES = 32 << 20
#: Share of the true nearest that the measured queries of a shard must find, and how many queries are measured.
RECALL, MEASURED = 0.96, 48


def diverse(sims: np.ndarray, among: np.ndarray, most: int) -> np.ndarray:
    """Choice (rows, candidates) of up to most candidates, best first, each nearer to the node
    than to those chosen before; free places go to the best of the rest. Candidates are sorted."""
    n, c = sims.shape
    chosen = np.zeros((n, c), bool)
    count = np.zeros(n, np.int64)
    valid = np.isfinite(sims)
    for j in range(c):
        ok = valid[:, j] & (count < most) & ~(chosen & (among[:, j, :] > sims[:, j, None])).any(1)
        chosen[:, j] = ok
        count += ok
    for j in range(c):
        ok = valid[:, j] & ~chosen[:, j] & (count < most)
        chosen[:, j] |= ok
        count += ok
    return chosen


class Graph:
    """Vectors (already given one length) with flat neighbour arrays per level."""

    def __init__(self, x: np.ndarray, nodes: list[np.ndarray], near: list[np.ndarray]):
        self.x, self.nodes, self.near = x, nodes, near

    def pick(self, sims: np.ndarray, ids: np.ndarray, most: int) -> np.ndarray:
        """Neighbour lists of rows from candidates (ids, -1 for none), in any order."""
        order = np.argsort(-sims, axis=1, kind="stable")
        sims, ids = np.take_along_axis(sims, order, 1), np.take_along_axis(ids, order, 1)
        out = np.full((len(ids), most), -1, np.int32)
        for lo in range(0, len(ids), 256):
            s, i = sims[lo : lo + 256], ids[lo : lo + 256]
            v = self.x[np.maximum(i, 0)]
            chosen = diverse(s, v @ v.transpose(0, 2, 1), most)
            spot = np.cumsum(chosen, 1) - 1
            r, c = np.nonzero(chosen)
            out[lo + r, spot[r, c]] = i[r, c]
        return out

    def link(self, level: int, new: np.ndarray, sims: np.ndarray, cand: np.ndarray, most: int) -> None:
        """Give the new nodes their neighbours, and those a link back."""
        near = self.near[level]
        mine = self.pick(sims, cand, most)
        near[new, : mine.shape[1]] = mine
        src, col = np.nonzero(mine >= 0)
        back, node = mine[src, col], new[src]
        s = np.einsum("ij,ij->i", self.x[self.nodes[level][back]] if level else self.x[back], self.x[self.nodes[level][node]] if level else self.x[node])
        order = np.lexsort((-s, back))
        back, node = back[order], node[order]
        rank = np.arange(len(back)) - np.searchsorted(back, back)
        keep = rank < most
        back, node, rank = back[keep], node[keep], rank[keep]
        touched, row = np.unique(back, return_inverse=True)
        both = np.full((len(touched), near.shape[1] + most), -1, np.int32)
        both[:, : near.shape[1]] = near[touched]
        both[row, near.shape[1] + rank] = node
        for lo in range(0, len(touched), 4096):
            b = both[lo : lo + 4096]
            x = self.x[self.nodes[level]] if level else self.x
            sim = np.where(b >= 0, np.einsum("ijk,ik->ij", x[np.maximum(b, 0)], x[touched[lo : lo + 4096]]), -np.inf)
            if level:
                self_x, self.x = self.x, x
                near[touched[lo : lo + 4096]] = self.pick(sim, b, near.shape[1])
                self.x = self_x
            else:
                near[touched[lo : lo + 4096]] = self.pick(sim, b, near.shape[1])

    def walk(self, q: np.ndarray, ef: int, limit: int | None = None, wide: int = 4) -> tuple[np.ndarray, np.ndarray]:
        """(similarity, node) of the ef best found for each query on the lowest level, best first."""
        n = limit or len(self.x)
        start = self.descend(q, n)
        near = self.near[0]
        rows = np.arange(len(q))
        seen = np.zeros(len(q) * n, bool)
        last = np.empty(len(q) * n, np.int32)  # which of one round's arrivals at a place came last
        ids = np.full((len(q), ef), -1, np.int32)
        sims = np.full((len(q), ef), -np.inf, np.float32)
        spent = np.ones((len(q), ef), bool)
        ids[:, 0], spent[:, 0] = start, False
        sims[:, 0] = np.einsum("ij,ij->i", q, self.x[start])
        worst = np.full(len(q), -np.inf, np.float32)
        seen[rows * n + start] = True
        live = rows
        while len(live):
            open_ = np.where(spent[live], -np.inf, sims[live])
            pick = np.argpartition(-open_, min(wide, ef) - 1, axis=1)[:, :wide]
            good = np.isfinite(np.take_along_axis(open_, pick, 1))
            some = good.any(1)
            live, pick, good = live[some], pick[some], good[some]
            if not len(live):
                break
            r, c = np.nonzero(good)
            from_, at = live[r], pick[r, c]
            spent[from_, at] = True
            hop = near[ids[from_, at]]
            what, flat = hop.reshape(-1), (from_[:, None] * n + hop).reshape(-1)
            ok = np.flatnonzero((what >= 0) & (what < n))
            ok = ok[~seen[flat[ok]]]
            flat = flat[ok]
            turn = np.arange(len(flat), dtype=np.int32)
            last[flat] = turn
            once = last[flat] == turn
            flat, what = flat[once], what[ok[once]]
            seen[flat] = True
            who = flat // n
            s = np.einsum("ij,ij->i", q[who], self.x[what])
            better = s > worst[who]
            who, what, s = who[better], what[better], s[better]
            if not len(who):
                continue
            rank = np.arange(len(who)) - np.searchsorted(who, who)
            hit, row = live, np.searchsorted(live, who)
            more = int(rank.max()) + 1
            s2, i2, p2 = np.full((len(hit), ef + more), -np.inf, np.float32), np.full((len(hit), ef + more), -1, np.int32), np.ones((len(hit), ef + more), bool)
            s2[:, :ef], i2[:, :ef], p2[:, :ef] = sims[hit], ids[hit], spent[hit]
            s2[row, ef + rank], i2[row, ef + rank], p2[row, ef + rank] = s, what, False
            keep = np.argpartition(-s2, ef - 1, axis=1)[:, :ef]
            sims[hit], ids[hit], spent[hit] = np.take_along_axis(s2, keep, 1), np.take_along_axis(i2, keep, 1), np.take_along_axis(p2, keep, 1)
            worst[hit] = sims[hit].min(1)
        order = np.argsort(-sims, axis=1, kind="stable")
        return np.take_along_axis(sims, order, 1), np.take_along_axis(ids, order, 1)

    def descend(self, q: np.ndarray, n: int) -> np.ndarray:
        """Greedy walk through the upper levels: an entry node of the lowest for each query."""
        at = np.zeros(len(q), np.int64)  # index within the level; node 0 is on all levels
        for level in range(len(self.near) - 1, 0, -1):
            nodes, near = self.nodes[level], self.near[level]
            best = np.einsum("ij,ij->i", q, self.x[nodes[at]])
            while True:
                hop = near[at]
                s = np.where((hop >= 0) & (nodes[np.maximum(hop, 0)] < n), np.einsum("ijk,ik->ij", self.x[nodes[np.maximum(hop, 0)]], q), -np.inf)
                j = s.argmax(1)
                up = s[np.arange(len(q)), j] > best
                if not up.any():
                    break
                best = np.where(up, s[np.arange(len(q)), j], best)
                at = np.where(up, hop[np.arange(len(q)), j], at)
            node = nodes[at]
            below = self.nodes[level - 1]
            at = np.searchsorted(below, node) if level > 1 else node
        return at


def build(x: np.ndarray, links: int = LINKS, ef: int = EF_BUILD, seed: int = 17) -> Graph:
    """HNSW over rows of x, all of one length."""
    n = len(x)
    height = np.minimum(np.floor(-np.log(np.random.default_rng(seed).random(n)) / math.log(links)), 8).astype(int)
    if n:
        height[0] = height.max()
    nodes, near = [np.arange(n)], [np.full((n, 2 * links), -1, np.int32)]
    g = Graph(x, nodes, near)
    for level in range(1, (height.max() if n else 0) + 1):
        own = np.flatnonzero(height >= level)
        nodes.append(own)
        sub = Graph(x[own], [np.arange(len(own))], [np.full((len(own), 2 * links), -1, np.int32)])
        insert(sub, ef, links)
        near.append(sub.near[0])
    insert(g, ef, links)
    return g


def insert(g: Graph, ef: int, links: int) -> None:
    """Fill the lowest level by batches; the upper levels, where filled, give the entries."""
    n, done = len(g.x), 0
    lone = Graph(g.x, [g.nodes[0]], [g.near[0]])
    while done < n:
        take = min(n - done, max(256, min(1024, done)))
        new = np.arange(done, done + take)
        q = g.x[new]
        own = q @ q.T
        own[np.arange(take), np.arange(take)] = -np.inf
        best = np.argpartition(-own, min(ef, take) - 1, axis=1)[:, : min(ef, take)]
        sims, ids = np.take_along_axis(own, best, 1), (best + done).astype(np.int32)
        if done:
            far = [(lone if done < 4096 or len(g.near) == 1 else g).walk(q[lo : lo + 256], ef, done) for lo in range(0, take, 256)]
            sims = np.concatenate([sims, np.concatenate([f[0] for f in far])], 1)
            ids = np.concatenate([ids, np.concatenate([f[1] for f in far])], 1)
            top = np.argpartition(-sims, ef - 1, axis=1)[:, :ef]
            sims, ids = np.take_along_axis(sims, top, 1), np.take_along_axis(ids, top, 1)
        lone.link(0, new, np.where(ids >= 0, sims, -np.inf), ids, links)
        done += take


def lengthened(x: np.ndarray) -> np.ndarray:
    """Rows over the greatest row's length, and one more coordinate that gives every row that length."""
    y = x / max(np.abs(x).max(initial=0), 5e-324)
    square = (y**2).sum(1)
    most = max(square.max(initial=0), 5e-324)
    return np.concatenate([y / math.sqrt(most), np.sqrt(np.maximum(1 - square / most, 0))[:, None]], 1).astype(np.float32)


TRIAL = pa.list_(pa.struct([("q", pa.int64()), ("id", pa.int64()), ("score", pa.float64()), ("width", pa.int32())]))
SHARD_ROW = pa.schema([("dim", pa.int32()), ("mag", pa.int32()), ("shard", pa.int32()), ("ids", pa.list_(pa.int64())), ("vectors", pa.binary()), ("nodes", pa.list_(pa.binary())), ("near", pa.list_(pa.binary())), ("trial", TRIAL)])
INDEX = "dim int, mag int, shard int, ids array<bigint>, vectors binary, nodes array<binary>, near array<binary>, trial array<struct<q: bigint, id: bigint, score: double, width: int>>"


def unfolded(vectors: pa.ChunkedArray, dim: int) -> np.ndarray:
    return np.asarray(vectors.combine_chunks().flatten()).astype(np.float64).reshape(-1, dim)


def directions(q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Queries over their largest component, and the same with the graph's further coordinate."""
    unit = q / np.maximum(np.abs(q).max(1, keepdims=True), 5e-324)
    return unit, np.concatenate([unit, np.zeros((len(q), 1))], 1).astype(np.float32)


def build_shard(t: pa.Table, sample: pa.Table | None = None, k: int = 0, ef: int = EF_SEARCH) -> pa.Table:
    """The shard's row; with sampled queries also what trials of its graph found."""
    t = t.sort_by("id").combine_chunks()
    d = t.column("dim")[0].as_py()
    x, ids = unfolded(t.column("vec"), d), np.asarray(t.column("id"))
    g = build(lengthened(x))
    trial = tried(g, x, ids, unfolded(sample.column("vec"), d), np.asarray(sample.column("id")), k, ef) if sample is not None and sample.num_rows else []
    row = {"dim": [d], "mag": [t.column("mag")[0].as_py()], "shard": [t.column("shard")[0].as_py()], "ids": [t.column("id").to_pylist()], "vectors": [x.tobytes()], "nodes": [[v.astype(np.int32).tobytes() for v in g.nodes]], "near": [[v.tobytes() for v in g.near]], "trial": [trial]}
    return pa.table(row, SHARD_ROW)


def tried(g: Graph, x: np.ndarray, ids: np.ndarray, q: np.ndarray, name: np.ndarray, k: int, ef: int) -> list[dict]:
    """The k largest inner products of each query, each with the least width of walk that finds it (None: none tried does).
    Nodes equal to the query are left out, since the walk to them is easy."""
    unit, flat = directions(q)
    scaled = x / max(np.abs(x).max(initial=0), 5e-324)
    best = by_products(unit, scaled, k)
    least = np.full(best.shape, -1, np.int32)
    while ef < len(x) or ef <= 2 * k:
        _, found = g.walk(flat, ef)
        for i in range(len(q)):
            least[i, (least[i] < 0) & np.isin(best[i], found[i])] = ef
        if share_found(unit, scaled, found[:, :k], k) >= RECALL:
            break
        ef *= 2
    with np.errstate(over="ignore", invalid="ignore"):
        score = np.einsum("ij,ikj->ik", q, x[best])
    i, j = np.nonzero((x[best] != q[:, None, :]).any(2))
    return [{"q": int(name[a]), "id": int(ids[best[a, b]]), "score": float(score[a, b]), "width": int(least[a, b]) if least[a, b] > 0 else None} for a, b in zip(i, j, strict=True)]


def walk_widths(built: DataFrame, k: int) -> DataFrame:
    """(dim, mag, width): the least width at which the graphs of a magnitude find enough of the sampled queries' k nearest over all shards."""
    trials = built.select("dim", "mag", F.explode("trial").alias("t")).select("dim", "mag", "t.*")
    rank = F.row_number().over(Window.partitionBy("dim", "q").orderBy(F.desc("score"), "id"))
    counts = trials.withColumn("r", rank).where(F.col("r") <= k).groupBy("dim", "mag", "width").agg(F.count("*").alias("n"))
    group = Window.partitionBy("dim", "mag")
    shares = counts.withColumn("upto", F.sum("n").over(group.orderBy(F.asc_nulls_last("width")))).withColumn("whole", F.sum("n").over(group))
    enough = F.col("width").isNotNull() & (F.col("whole") >= MEASURED) & (F.col("upto") >= RECALL * F.col("whole"))
    return shares.where(enough).groupBy("dim", "mag").agg(F.min("width").alias("width"))


def by_products(q: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """(queries, k) nodes with the largest inner products, all of them looked at."""
    k, out = min(k, len(x)), []
    for lo in range(0, len(q), max(1, (1 << 22) // len(x))):
        s = q[lo : lo + max(1, (1 << 22) // len(x))] @ x.T
        out.append(np.argpartition(-s, k - 1, axis=1)[:, :k])
    return np.concatenate(out) if out else np.zeros((0, k), np.int64)


def share_found(q: np.ndarray, x: np.ndarray, found: np.ndarray, k: int) -> float:
    """Of the k largest inner products of each query, the share that the found nodes (-1 for none) reach."""
    best = -np.sort(-np.take_along_axis(q @ x.T, by_products(q, x, k), 1), axis=1)
    got = np.where(found >= 0, np.einsum("ij,ikj->ik", q, x[np.maximum(found, 0)]), -np.inf)
    got = -np.sort(-got, axis=1)[:, : best.shape[1]]
    return float((got >= best - 1e-12 * np.abs(best)).mean()) if best.size else 1.0


def measured_width(g: Graph, flat: np.ndarray, q: np.ndarray, x: np.ndarray, k: int, ef: int) -> int | None:
    """Width of the walk at which a sample of the queries is answered well enough; None if that is no walk any more."""
    some = np.unique(np.linspace(0, len(q) - 1, min(len(q), MEASURED)).astype(int))
    while ef < len(x) or ef <= 2 * k:
        _, found = g.walk(flat[some], ef)
        if share_found(q[some], x, found[:, :k], k) >= RECALL:
            return ef
        ef *= 2
    return None


def search_shard(k: int, ef: int):
    def run(index: pa.Table, queries: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if index.num_rows and queries.num_rows:
            row = index.slice(0, 1).to_pylist()[0]
            ids, x = np.array(row["ids"]), np.frombuffer(row["vectors"], np.float64).reshape(len(row["ids"]), -1)
            nodes = [np.frombuffer(v, np.int32).astype(np.int64) for v in row["nodes"]]
            near = [np.frombuffer(v, np.int32).reshape(len(m), -1) for v, m in zip(row["near"], nodes, strict=True)]
            g = Graph(lengthened(x), nodes, near)
            queries = queries.combine_chunks()
            q = unfolded(queries.column("vec"), x.shape[1])
            name = np.asarray(queries.column("id"))
            unit, flat = directions(q)
            scaled = x / max(np.abs(x).max(initial=0), 5e-324)
            width = row.get("width") or measured_width(g, flat, unit, scaled, k, max(ef, k))
            for lo in range(0, len(q), 256):
                found = by_products(unit[lo : lo + 256], scaled, k) if width is None else g.walk(flat[lo : lo + 256], width)[1]
                r, c = np.nonzero(found >= 0)
                node = found[r, c]
                with np.errstate(over="ignore", invalid="ignore"):
                    score = (q[lo + r] * x[node]).sum(1)
                order = np.lexsort((ids[node], -score, r))
                r, node, score = r[order], node[order], score[order]
                top = np.arange(len(r)) - np.searchsorted(r, r) < k
                out.append((name[lo + r[top]], ids[node[top]], score[top]))
        a, b, s = (np.concatenate(v) for v in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(s, pa.float64())], ["q", "id", "score"])

    return run


def vector_classes(rows: DataFrame, k: int) -> DataFrame:
    """(vec, dim, id, members): each distinct vector with its least id and its k + 1 least ids,
    gathered in two steps, so that a hot vector is cut down before its parts meet."""
    salt = F.pmod(F.xxhash64("id"), F.lit(width(rows.sparkSession)))
    cut = lambda ids: F.slice(F.array_sort(ids), 1, k + 1)
    part = rows.groupBy("vec", salt.alias("salt")).agg(cut(F.collect_set("id")).alias("ids"))
    whole = part.groupBy("vec").agg(cut(F.array_distinct(F.flatten(F.collect_list("ids")))).alias("members"))
    top = F.array_max(F.transform("vec", lambda x: F.abs(x)))
    # the largest component is bound once, not worked out again for each of the others
    log = F.transform(F.array(top), lambda t: F.log2(t) + F.log2(F.aggregate("vec", F.lit(0.0), lambda s, x: s + (x / t) * (x / t))) / 2)[0]
    mag = F.floor(log + 0.5).cast("int")  # unit vectors lie in the middle of a magnitude
    return whole.select("vec", F.size("vec").alias("dim"), mag.alias("mag"), F.col("members")[0].alias("id"), "members")


def usable(table: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    finite = F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return by_position(table).select(column(table, id_col).cast("long").alias("id"), column(table, vec_col).cast("array<double>").alias("vec")).where(F.col("id").isNotNull() & F.col("vec").isNotNull() & (F.size("vec") > 0)).where(F.coalesce(finite, F.lit(False)) & F.exists("vec", lambda x: x != 0))


def dealt_shards(classes: DataFrame) -> DataFrame:
    """(dim, mag, shards): one row per length and magnitude of vectors, a few thousand at most for one length."""
    n = F.col("n")
    shards = F.greatest(F.ceil(n / SHARD), F.least(F.lit(LEAST_SHARDS), F.ceil(n / LEAST)))
    return settled(classes.groupBy("dim", "mag").agg(F.count("*").alias("n")).select("dim", "mag", shards.cast("int").alias("shards")))


def index(classes: DataFrame, sizes: DataFrame, sample: DataFrame, k: int, ef: int) -> DataFrame:
    """One row of flat arrays per shard, with the trials of the sampled queries (id, dim, vec). Shards get partitions of
    their own number, since building one takes much longer than its bytes suggest."""
    keys, theirs = ["dim", "mag", "shard"], ["of_dim", "of_mag", "of_shard"]
    parts = min(2 * (sizes.agg(F.sum("shards")).first()[0] or 1), MOST_PARTS)
    dealt = classes.join(sizes, ["dim", "mag"]).select("dim", "mag", F.pmod(F.xxhash64("vec"), "shards").cast("int").alias("shard"), "id", "vec")
    each = F.explode(F.sequence(F.lit(0), F.col("shards") - 1))
    asked = sample.join(sizes.withColumnsRenamed({"dim": "of_dim", "mag": "of_mag"}), F.col("dim") == F.col("of_dim")).select("of_dim", "of_mag", each.alias("of_shard"), "id", "vec")

    def run(t: pa.Table, sample: pa.Table) -> pa.Table:
        return build_shard(t, sample, k, ef) if t.num_rows else SHARD_ROW.empty_table()

    return dealt.repartition(parts, *keys).groupBy(*keys).cogroup(asked.repartition(parts, *theirs).groupBy(*theirs)).applyInArrow(run, INDEX)


def sampled(forms: DataFrame) -> DataFrame:
    """(id, dim, vec) of a fixed number of queries of each length, by a hash."""
    rank = F.row_number().over(Window.partitionBy("dim").orderBy(F.xxhash64("q"), "q"))
    return forms.withColumn("r", rank).where(F.col("r") <= MEASURED).select(F.col("q").alias("id"), "dim", "vec")


def nearest(table: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", ef: int = EF_SEARCH) -> DataFrame:
    """(query_id, rank, id, score): for each query (a row of the same form), its k nearest among the rows of table but itself."""
    rows = usable(table, id_col, vec_col)
    classes = settled(vector_classes(rows, k))
    sizes = dealt_shards(classes)
    asked = usable(queries, id_col, vec_col).select(F.col("id").alias("query_id"), "vec").distinct()
    # each distinct vector asks once
    forms = settled(asked.groupBy("vec").agg(F.min("query_id").alias("q")).withColumn("dim", F.size("vec")))
    total = forms.agg(F.sum(8 * F.col("dim"))).first()[0] or 0
    blocks = max(1, math.ceil(total / QUERY_BYTES))
    built = settled(index(classes, sizes, sampled(forms), k, max(ef, k + 1)))
    per_shard = built.join(walk_widths(built, k), ["dim", "mag"], "left").drop("trial").withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    spread = forms.join(sizes, "dim").select("dim", "mag", F.pmod(F.xxhash64("q"), F.lit(blocks)).cast("int").alias("block"), F.col("q").alias("id"), "vec", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("shard"))
    keys = ["dim", "mag", "shard", "block"]
    found = per_shard.groupBy(*keys).cogroup(spread.groupBy(*keys)).applyInArrow(search_shard(k + 1, ef), "q long, id long, score double")
    best = F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), "id"))
    top = found.withColumn("r", best).where(F.col("r") <= k + 1).join(classes.select("id", "members"), "id").select("q", "score", "members")
    pairs = asked.join(forms.select("vec", "q"), "vec").select("query_id", "q").join(top, "q").select("query_id", "score", F.explode("members").alias("id")).where("id <> query_id").groupBy("query_id", "id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "id"))
    return pairs.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias(id_col), "score")
