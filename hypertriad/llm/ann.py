"""Approximate nearest neighbours by learned partitions.

A bounded sample of distinct vectors gives an exact neighbour graph, the graph is cut into balanced parts (balanced
seeding, then capacity-bounded moves that raise the number of edges inside parts), and a small network learns which part
a vector belongs to, from the parts of the vector and its neighbours.  Every row is indexed: it goes to its most probable
part, and parts that are large are cut again in the same way.  A query goes to its most probable parts, as many as held-out
vectors with their exact neighbours among all rows show to be needed, and is ranked exactly, in double precision, against
the rows there.  Parts and their queries are cut into blocks, so a crowded part (many copies of a vector) is many tasks and
no task holds more than one block of rows and one of queries.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored, row_uid

#: Vectors a graph and a network are fitted on, and those held out to choose the number of parts to probe, at most.
SAMPLE, CALIBRATION = 8_000, 256
NEIGHBOURS = 10
#: Vectors of the sample for each part.
SAMPLE_A_PART = 10
HIDDEN = 64
#: Share of the held-out vectors' neighbours that the probed parts must hold.
AIM = 0.925
#: Parts of more rows on average are cut again.
SPLIT_ROWS = 4_000
#: Rows and queries that a task compares, on average at most.
BLOCK_ROWS, QUERY_ROWS = 4_000, 4_000
#: Tasks that the queries of one part of the first level are dealt to.
SPREAD = 8


def exact_neighbours(x: np.ndarray, k: int) -> np.ndarray:
    """The k nearest other rows of every row, in blocks."""
    out, sq = np.empty((len(x), k), np.int64), (x * x).sum(axis=1)
    for a in range(0, len(x), 512):
        d = sq[None, :] - 2 * x[a : a + 512] @ x.T
        d[np.arange(len(d)), a + np.arange(len(d))] = np.inf
        out[a : a + 512] = np.argpartition(d, k, axis=1)[:, :k] if k < len(x) - 1 else np.argsort(d, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, near: np.ndarray, parts: int, rounds: int = 12, seed: int = 1) -> np.ndarray:
    """Parts of nearly equal size with few graph edges between them."""
    r = np.random.default_rng(seed)
    n, room = len(x), int(np.ceil(len(x) / parts * 1.05))
    centres = x[r.choice(n, parts, replace=False)]
    for _ in range(8):  # balanced seeding: the surest rows choose first
        d = (centres * centres).sum(axis=1)[None, :] - 2 * x @ centres.T
        order = np.argsort(np.partition(d, min(1, parts - 1), axis=1)[:, 0] - d.mean(axis=1))
        part, size, choice = np.full(n, -1), np.zeros(parts, int), np.argsort(d, axis=1)
        for i in order:
            for p in choice[i]:
                if size[p] < room:
                    part[i], size[p] = p, size[p] + 1
                    break
        centres = np.array([x[part == p].mean(axis=0) if (part == p).any() else x[r.integers(n)] for p in range(parts)])
    both = np.concatenate([np.stack([np.repeat(np.arange(n), near.shape[1]), near.ravel()], 1), np.stack([near.ravel(), np.repeat(np.arange(n), near.shape[1])], 1)])
    both = both[np.argsort(both[:, 0], kind="stable")]
    bounds = np.searchsorted(both[:, 0], np.arange(n + 1))
    for _ in range(rounds):
        moved = 0
        for i in r.permutation(n):
            votes = np.bincount(part[both[bounds[i] : bounds[i + 1], 1]], minlength=parts)
            votes[size >= room] = -1
            votes[part[i]] = max(votes[part[i]], np.count_nonzero(part[both[bounds[i] : bounds[i + 1], 1]] == part[i]))
            to = int(votes.argmax())
            if votes[to] > votes[part[i]]:
                size[part[i]] -= 1
                size[to] += 1
                part[i] = to
                moved += 1
        if moved < n / 200:
            break
    return part


@dataclass
class Router:
    """A small network over parts: a linear layer, which starts at the parts' means, and a hidden one beside it."""

    mean: np.ndarray
    scale: float
    w: np.ndarray
    b: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray

    @property
    def parts(self) -> int:
        return len(self.b)

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = (x - self.mean) / self.scale
        return z @ self.w + self.b + np.maximum(z @ self.w1 + self.b1, 0) @ self.w2

    def ranked(self, x: np.ndarray) -> np.ndarray:
        return np.argsort(-self.scores(x), axis=1, kind="stable")

    def home(self, x: np.ndarray) -> np.ndarray:
        return self.scores(x).argmax(axis=1)


def learn(x: np.ndarray, near: np.ndarray, part: np.ndarray, parts: int, epochs: int = 5, rate: float = 0.001, noise: float = 1.0, seed: int = 2) -> Router:
    """Softmax classifier of parts; a row's target is shared by its own part and its neighbours', and its input is shaken
    anew in every epoch, so that the network learns regions and not rows."""
    r = np.random.default_rng(seed)
    target = np.zeros((len(x), parts), np.float32)
    np.add.at(target, (np.arange(len(x)), part), near.shape[1])
    for j in range(near.shape[1]):
        np.add.at(target, (np.arange(len(x)), part[near[:, j]]), 1)
    target /= target.sum(axis=1, keepdims=True)
    dim, mean, scale = x.shape[1], x.mean(axis=0), float(x.std()) or 1.0
    z = (x - mean) / scale
    means = np.array([z[part == p].mean(axis=0) if (part == p).any() else z[0] for p in range(parts)])
    means /= np.maximum(np.linalg.norm(means, axis=1, keepdims=True), 1e-9)
    net = Router(mean, scale, means.T * 0.5, np.zeros(parts), r.standard_normal((dim, HIDDEN)) * dim**-0.5, np.zeros(HIDDEN), np.zeros((HIDDEN, parts)))
    names = ("w", "b", "w1", "b1", "w2")
    m1, m2, t = {k: 0.0 for k in names}, {k: 0.0 for k in names}, 0
    for _ in range(epochs):
        for at in np.array_split(r.permutation(len(x)), max(1, len(x) // 256)):
            y = z[at] + noise * r.standard_normal((len(at), dim))
            h = np.maximum(y @ net.w1 + net.b1, 0)
            s = y @ net.w + net.b + h @ net.w2
            e = np.exp(s - s.max(axis=1, keepdims=True))
            d = (e / e.sum(axis=1, keepdims=True) - target[at]) / len(at)
            dh = (d @ net.w2.T) * (h > 0)
            t += 1
            for k, g in (("w", y.T @ d), ("b", d.sum(axis=0)), ("w2", h.T @ d), ("w1", y.T @ dh), ("b1", dh.sum(axis=0))):
                m1[k] = 0.9 * m1[k] + 0.1 * g
                m2[k] = 0.999 * m2[k] + 0.001 * g * g
                setattr(net, k, getattr(net, k) - rate * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.999**t)) + 1e-8))
    return net


def fit(sample: np.ndarray) -> Router:
    """Router over the balanced parts of a sample of distinct vectors."""
    parts = len(sample) // SAMPLE_A_PART
    if parts < 2:
        dim = sample.shape[1] if len(sample) else 1
        return Router(np.zeros(dim), 1.0, np.zeros((dim, 1)), np.zeros(1), np.zeros((dim, 1)), np.zeros(1), np.zeros((1, 1)))
    near = exact_neighbours(sample, min(NEIGHBOURS, len(sample) - 1))
    return learn(sample, near, balanced_parts(sample, near, parts), parts)


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and the vector in doubles of the rows that take part: no null, zero or non-finite ones; the dimension is the
    commonest one (the least of these, if several)."""
    x = F.transform("embedding", lambda v: v.cast("double"))
    fine = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists("x", lambda v: v != 0)
    able = vectors.select(F.col("vec_id").cast("long"), x.alias("x")).where(F.col("vec_id").isNotNull() & fine)
    top = able.groupBy(F.size("x").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "d").first()
    return able.where(F.size("x") == (top["d"] if top else 0))


def _drawn(rows: DataFrame, count: int) -> tuple[np.ndarray, np.ndarray]:
    """A sample to fit on and vectors held out from it: at most SAMPLE and CALIBRATION distinct ones, by a hash of the vector
    (equal vectors fall on one side)."""
    place, spread = F.pmod(F.xxhash64("x"), F.lit(1_000_003)), 1_000_003
    held = min(0.15, 1.3 * CALIBRATION / max(1, count))
    able = rows.select("x", place.alias("h"))
    pick = lambda df, n: df.distinct().orderBy(F.xxhash64("x", F.lit(1)), "x").limit(n).collect()
    test = pick(able.where(F.col("h") < held * spread).select("x"), CALIBRATION)
    share = held + min(1 - held, 1.3 * SAMPLE / max(1, count))
    fitted = pick(able.where((F.col("h") >= held * spread) & (F.col("h") < share * spread)).select("x"), SAMPLE)
    as_rows = lambda got: np.array([r["x"] for r in got]) if got else np.zeros((0, 1))
    return as_rows(fitted), as_rows(test)


def _nearest(q: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, barred: np.ndarray | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each row of q the places of its k nearest rows of x (ties: least id) and their exact distances.  A matrix product
    names those that can be among them, and only these are measured.  barred[i, j]: row j is none of query i's."""
    out, sq = [], (x * x).sum(axis=1)
    for a in range(0, len(q), 256):
        part = q[a : a + 256]
        d = sq[None, :] - 2 * part @ x.T + (part * part).sum(axis=1)[:, None]
        if barred is not None:
            d[barred[a : a + 256]] = np.inf
        most = np.partition(d, k - 1, axis=1)[:, k - 1] if d.shape[1] > k else np.full(len(part), np.inf)
        slack = 1e-9 * (sq.max(initial=0) + (part * part).sum(axis=1)) + 1e-300
        for v, row, top in zip(part, d, most + slack):
            able = np.flatnonzero((row <= top) & (row < np.inf))
            exact = np.sqrt(((x[able] - v) ** 2).sum(axis=1))
            best = np.lexsort((ids[able], exact))[:k]
            out.append((able[best], exact[best]))
    return out


def _true_neighbours(placed: DataFrame, test: np.ndarray, k: int, keys: list[str]) -> list:
    """(query, rank and the key columns) of the exact k nearest rows of every held-out vector, over all rows."""
    sent = placed.sparkSession.sparkContext.broadcast(test)  # CALIBRATION vectors at most

    def best(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                x, ids = np.stack(b.x.to_list()), b.vec_id.to_numpy()
                got = _nearest(sent.value, x, ids, k + 1)  # a held-out vector is a row itself, at distance 0
                at, far = np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got])
                yield pd.DataFrame({"q": np.repeat(np.arange(len(got)), [len(g[0]) for g in got]), "d": far} | {c: b[c].to_numpy()[at] for c in ("vec_id", *keys)})

    kinds = {**dict(placed.dtypes)}
    found = placed.mapInPandas(best, "q int, d double, vec_id long, " + ", ".join(f"{c} {kinds[c]}" for c in keys))
    order = Window.partitionBy("q").orderBy("d", "vec_id")
    return found.where("d > 0").withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("q", *keys).collect()  # k rows for each vector


def _probes(net: Router, test: np.ndarray, found: list, aim: float) -> int:
    """The least number of parts that reaches ``aim`` of the true neighbours of held-out vectors."""
    if not found or net.parts == 1:
        return net.parts
    place = np.argsort(net.ranked(test), axis=1)
    at = place[[r["q"] for r in found], [r["part"] for r in found]]
    reach = np.bincount(at, minlength=net.parts).cumsum() / len(at)
    return int(np.searchsorted(reach, aim - 1e-12) + 1)


def _enough(ranked: np.ndarray, sizes: np.ndarray, probes: int, k: int) -> list[np.ndarray]:
    """Each query's parts: the first ``probes``, and on until they hold more rows than k and its own."""
    held = sizes[ranked].cumsum(axis=1)
    need = np.maximum(probes, (held <= 3 * k).sum(axis=1) + 1)
    return [r[:n] for r, n in zip(ranked, need)]


@dataclass
class Index:
    """Rows by leaf.  ``placed``: vec_id, x, leaf; ``route(queries)`` adds the leaves (array) a query goes to."""

    placed: DataFrame
    route: Callable[[DataFrame], DataFrame]
    parts: int
    probes: int
    levels: int


def _per_vector(fit_: Callable[[np.ndarray], list | np.ndarray], kind: str) -> Callable:
    @F.pandas_udf(kind)
    def run(x: pd.Series) -> pd.Series:
        out = []
        for a in range(0, len(x), 4096):
            out += list(fit_(np.stack(x.iloc[a : a + 4096].to_list())))
        return pd.Series(out, dtype=object if kind.startswith("array") else "int64")

    return run


def build_index(rows: DataFrame, store: Stored, k: int = 10) -> Index:
    """All ``rows`` (vec_id, x; stored) dealt to the leaves of a learned partition.

    The first cut is fitted on a bounded sample.  While parts are larger than SPLIT_ROWS on average, each part is cut again
    by a router of its own, fitted in its own task on a bounded sample of the part; so leaves stay small as rows grow.
    The numbers of parts to probe come from held-out vectors' exact neighbours among all rows, and not from the sample.
    """
    spark = rows.sparkSession
    n = rows.count()
    sample, test = _drawn(rows, n)
    net = fit(sample)
    sent = spark.sparkContext.broadcast(net)
    placed = store.put(rows.withColumn("part", _per_vector(lambda x: sent.value.home(x), "long")("x")))
    counted = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each part of one router
    sizes = np.array([counted.get(p, 0) for p in range(net.parts)])
    twice = n / net.parts > SPLIT_ROWS
    found = _true_neighbours(placed, test, k, ["part"]) if len(test) else []
    probes = _probes(net, test, found, AIM**0.5 if twice else AIM)
    first = _per_vector(lambda x: _enough(sent.value.ranked(x), sizes, probes, k), "array<long>")
    if not twice:
        placed = placed.withColumnRenamed("part", "leaf")
        return Index(placed, lambda q: q.withColumn("leaves", first("x")), net.parts, probes, 1)
    return _cut_again(placed, first, sizes, test, net.parts, probes, store, k)


def _cut_again(placed: DataFrame, first: Callable, sizes: np.ndarray, test: np.ndarray, parts: int, probes: int, store: Stored, k: int) -> Index:
    """The second level: a router for each part, kept in a table beside its part and never gathered."""
    spark = placed.sparkSession
    share = F.element_at(F.array(*[F.lit(min(1.0, 1.3 * SAMPLE / max(1, int(s)))) for s in sizes]), (F.col("part") + 1).cast("int"))
    some = placed.where(F.pmod(F.xxhash64("x", F.lit(2)), F.lit(1_000_003)) < share * 1_000_003).select("part", "x").distinct()

    def fitted(pdf: pd.DataFrame) -> pd.DataFrame:
        by_hash = sorted((np.asarray(v) for v in pdf.x), key=lambda v: (zlib.crc32(v.tobytes()), v.tobytes()))
        return pd.DataFrame({"part": [pdf.part.iloc[0]], "net": [pickle.dumps(fit(np.stack(by_hash[:SAMPLE])))]})

    nets = store.put(some.groupBy("part").applyInPandas(fitted, "part long, net binary"))
    wide = SAMPLE // SAMPLE_A_PART + 1  # leaves of a part at most, so leaf numbers are unique
    cuts = F.element_at(F.array(*[F.lit(max(1, -(-int(s) // (4 * BLOCK_ROWS)))) for s in sizes]), (F.col("part") + 1).cast("int"))

    def homes(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left):
            return pd.DataFrame({"vec_id": [], "x": [], "leaf": []}).astype({"vec_id": "int64", "x": object, "leaf": "int64"})
        net = pickle.loads(right.net.iloc[0])
        return pd.DataFrame({"vec_id": left.vec_id, "x": left.x, "leaf": left.part * wide + net.home(np.stack(left.x.to_list()))})

    dealt = placed.withColumn("cut", F.pmod(F.xxhash64("vec_id"), cuts))
    beside = nets.withColumn("cut", F.explode(F.sequence(F.lit(0).cast("long"), cuts.cast("long") - 1)))
    leaves = store.put(dealt.groupBy("part", "cut").cogroup(beside.groupBy("part", "cut")).applyInPandas(homes, "vec_id long, x array<double>, leaf long"))
    held = leaves.groupBy("leaf").agg(F.count(F.lit(1)).alias("n")).select(F.expr(f"leaf div {wide}").alias("part"), F.struct(F.expr(f"leaf % {wide}").alias("p"), "n").alias("s"))
    nets = store.put(nets.join(held.groupBy("part").agg(F.collect_list("s").alias("sizes")), "part"))  # SAMPLE / SAMPLE_A_PART sizes a part at most

    def ranked(q: DataFrame, probes_inside: int | None) -> DataFrame:
        """q (uid, x) with every leaf it goes to inside the parts of the first level; None: all, in order."""

        def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
            if not len(left) or not len(right):
                return pd.DataFrame({"uid": [], "found": []}).astype({"uid": "int64", "found": object})
            net = pickle.loads(right.net.iloc[0])
            size = np.zeros(net.parts, np.int64)
            for s in right.sizes.iloc[0]:
                size[s["p"]] = s["n"]
            order = net.ranked(np.stack(left.x.to_list()))
            got = list(order) if probes_inside is None else _enough(order, size, min(probes_inside, net.parts), k)
            return pd.DataFrame({"uid": left.uid, "found": [g.astype(np.int64) + left.part.iloc[0] * wide for g in got]})

        asked = q.select("uid", "x", F.explode(first("x")).alias("part")).withColumn("cut", F.pmod(F.xxhash64("uid"), F.lit(SPREAD)))
        nets_ = nets.withColumn("cut", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SPREAD).cast("long") - 1)))
        return asked.groupBy("part", "cut").cogroup(nets_.groupBy("part", "cut")).applyInPandas(run, "uid long, found array<long>")

    asking = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(test)], "uid long, x array<double>")
    want = {}
    for r in _true_neighbours(leaves, test, k, ["leaf"]) if len(test) else []:
        want.setdefault((r["q"], r["leaf"] // wide), []).append(r["leaf"])
    at = []
    for r in ranked(asking, None).collect():  # CALIBRATION vectors, once for each part that they probe
        place = {leaf: i for i, leaf in enumerate(r["found"])}
        at += [place[leaf] for leaf in want.get((r["uid"], r["found"][0] // wide), [])]
    inside = int(np.searchsorted(np.bincount(at).cumsum() / len(at), AIM**0.5 - 1e-12) + 1) if at else 1

    def route(q: DataFrame) -> DataFrame:
        found = ranked(q.select("uid", "x"), inside).groupBy("uid").agg(F.flatten(F.collect_list("found")).alias("leaves"))
        return q.join(found, "uid")

    return Index(leaves, route, parts, probes, 2)


def search(vectors: DataFrame, k: int = 10, every: int = 100) -> DataFrame:
    """query_id, rank, vec_id and score of the k nearest rows found for each query (vec_id divisible by ``every``).

    Repeated vec_ids are repeated candidates; rows with the query's own vec_id are none.  Equal query rows are one query;
    a query's vec_id with several vectors is as many queries, each with ranks of its own.  Ties go to the smaller vec_id.
    Fewer than k candidates in all: all are returned.  Empty table: empty result.
    """
    store = Stored(vectors.sparkSession)
    rows = store.put(usable(vectors).withColumn("uid", row_uid()))
    index = build_index(rows.drop("uid"), store, k)
    asking = store.put(rows.where(F.col("vec_id") % every == 0).groupBy("vec_id", "x").agg(F.min("uid").alias("uid")))
    return rerank(index, index.route(asking), store, k)


def rerank(index: Index, asking: DataFrame, store: Stored, k: int) -> DataFrame:
    """Exact ranks of the rows in each query's leaves.  Leaves lie together in units of about BLOCK_ROWS rows; larger ones
    are cut, and so are the queries of a unit, so a task compares one block of rows with one of queries."""
    held = index.placed.groupBy("leaf").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("leaf").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row for each leaf
    units = store.put(held.select("leaf", F.floor(before / BLOCK_ROWS).alias("unit"), F.ceil(F.col("n") / BLOCK_ROWS).alias("cuts")))
    wanted = store.put(asking.select("uid", F.col("vec_id").alias("query_id"), F.col("x").alias("q"), F.explode("leaves").alias("leaf")).join(units, "leaf").groupBy("uid", "query_id", "q", "unit").agg(F.collect_set("leaf").alias("leaves"), F.max("cuts").alias("cuts")))
    blocks = wanted.groupBy("unit").agg(F.ceil(F.count(F.lit(1)) / QUERY_ROWS).alias("turns"))
    each = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), n - 1))
    base = index.placed.join(units, "leaf").join(blocks, "unit").select("vec_id", "x", "leaf", "unit", F.pmod(F.xxhash64("vec_id"), F.col("cuts")).alias("cut"), each(F.col("turns")).alias("turn"))
    queries = wanted.join(blocks, "unit").select("uid", "query_id", "q", "leaves", "unit", F.pmod(F.xxhash64("uid"), F.col("turns")).alias("turn"), each(F.col("cuts")).alias("cut"))

    def nearest(q: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(q) and len(b):
            ids, x, leaf = b.vec_id.to_numpy(), np.stack(b.x.to_list()), b.leaf.to_numpy()
            own, at = np.unique(leaf, return_inverse=True)
            for a in range(0, len(q), 256):
                some = q.iloc[a : a + 256]
                open_ = np.zeros((len(some), len(own)), bool)
                for i, leaves in enumerate(some.leaves):
                    open_[i, np.isin(own, leaves, assume_unique=True)] = True
                barred = ~open_[:, at] | (ids[None, :] == some.query_id.to_numpy()[:, None])
                got = _nearest(np.stack(some.q.to_list()), x, ids, k, barred)
                each_ = [len(g[0]) for g in got]
                out.append(pd.DataFrame({"uid": np.repeat(some.uid.to_numpy(), each_), "query_id": np.repeat(some.query_id.to_numpy(), each_), "vec_id": ids[np.concatenate([g[0] for g in got])], "score": np.concatenate([g[1] for g in got])}))
        return pd.concat(out) if out else pd.DataFrame({"uid": [], "query_id": [], "vec_id": [], "score": []}).astype({"uid": "int64", "query_id": "int64", "vec_id": "int64"})

    keys = ("unit", "cut", "turn")
    found = queries.groupBy(*keys).cogroup(base.groupBy(*keys)).applyInPandas(nearest, "uid long, query_id long, vec_id long, score double")
    order = Window.partitionBy("uid").orderBy("score", "vec_id")  # k rows from each block of a query's leaves
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
