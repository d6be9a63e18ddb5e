"""Counts of links and triads without a table of links or lead pairs: exact, for inputs whose pairs outgrow the disk.

Edges are laid out as types: the vertices that some other edge also holds, as codes, and whether there are private ones
besides.  No overlap and no region of a triad tells edges of one type apart, so types are compared and their edges counted.
A block of types goes to one task with every type that shares a vertex with one of them, each once and with its codes;
there, each type leads the triads whose other two types come later, in the order of (bound on its links, id).

types  t BIGINT, codes ARRAY<INT> sorted, own INT (1: private vertices), m BIGINT (edges), bound BIGINT
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.patterns import PATTERN_TABLE
from ..model import Hypergraph
from ..stages import stage

#: Leading types of one task, and tasks for each core.
LEADS = 2_000
TASKS = 3
#: Codes that a task holds at once where only links are counted, or that a block of near edges may meet.
HELD = 3_000_000
#: Leading edges of a block of near edges.
NEAR = 100_000
#: Entries of a comparison that stay in a core's cache.
CELLS = 1 << 16
#: Types up to which a task holds all their overlaps as one matrix, and vertices up to which it holds types as bits.
MATRIX = 8_000
BITS = 256

_OPEN = 127  # no triad has this signature
_BY_SIGNATURE = {s[1] * 32 + s[2] * 16 + s[3] * 4 + s[4]: p for p, s in PATTERN_TABLE.items()}


def vertex_codes(hg: Hypergraph) -> DataFrame:
    """(v, code INT, d): numbers from 0 for the vertices of two edges at least."""
    met = hg.incidence.groupBy("v").agg(F.count(F.lit(1)).alias("d")).where("d > 1")
    laid = stage(met.withColumn("_c", F.monotonically_increasing_id()))  # partition in the bits from 33 on, place in those below
    parts = sorted((r["p"], r["n"]) for r in laid.groupBy(F.shiftright("_c", 33).alias("p")).agg(F.count(F.lit(1)).alias("n")).collect())  # a row for each partition
    starts, at = [], 0
    for p, n in parts:
        starts += [F.lit(p), F.lit(at)]
        at += n
    if at >= 2**31:
        raise ValueError(f"{at} shared vertices")
    start = F.element_at(F.create_map(*starts), F.shiftright("_c", 33)) if parts else F.lit(0)
    return laid.select("v", (start + F.col("_c").bitwiseAND(2**33 - 1)).cast("int").alias("code"), "d")


def edge_types(hg: Hypergraph) -> tuple[DataFrame, DataFrame]:
    """(types, edges with the codes and own of their type); edges that share no vertex are left out."""
    codes = vertex_codes(hg)
    at = hg.incidence.join(codes, "v").groupBy("e").agg(F.sort_array(F.collect_list("code")).alias("codes"), F.sum(F.col("d") - 1).alias("bound"))
    edges = stage(at.join(hg.sizes, "e").select("e", "codes", (F.col("n") > F.size("codes")).cast("int").alias("own"), "bound"))
    types = edges.groupBy("codes", "own").agg(F.count(F.lit(1)).alias("m"), F.first("bound").alias("bound"))
    return stage(types.withColumn("t", F.monotonically_increasing_id())), edges


def _dealt(types: DataFrame, sliced: bool = False) -> DataFrame:
    """Types by block ``b`` and slice ``s``: the block's own ones (lead) and those that share a vertex with one of them
    (other).  sliced: where a task would hold more than ``HELD`` codes, the others are cut into slices, each with all leads."""
    cores = types.sparkSession.sparkContext.defaultParallelism
    seen = types.agg(F.count(F.lit(1)).alias("t"), F.sum(F.size("codes")).alias("codes"), F.avg("bound").alias("bound")).first()
    blocks = max(TASKS * cores, -(-seen["t"] // LEADS))
    block = F.pmod(F.xxhash64("t"), F.lit(blocks)).cast("int")
    at = types.select("t", block.alias("b"), F.explode("codes").alias("v"))
    met = at.select("b", "v").distinct().join(at.select("v", "t"), "v").select("b", "t").distinct()
    rows = met.join(types, "t").withColumn("lead", F.col("b") == block)
    held = min(seen["codes"], seen["bound"] * seen["codes"] / blocks) if sliced and seen["t"] else 0
    slices = max(1, int(-(-held // HELD)))
    if slices == 1:
        return rows.select("*", F.lit(0).alias("s"), F.lit(True).alias("other")).repartition(blocks, "b")
    own = F.pmod(F.xxhash64("t", F.lit(1)), F.lit(slices)).cast("int")
    to = F.when(F.col("lead"), F.sequence(F.lit(0), F.lit(slices - 1))).otherwise(F.array(own))
    return rows.withColumn("s", F.explode(to)).withColumn("other", F.col("s") == own).repartition(blocks * slices, "b", "s")


def dealt_near(hg: Hypergraph) -> DataFrame:
    """(b, t, codes, lead): edges as ``_dealt`` deals types, with their members for codes (``as_types`` adds the rest).  Blocks are
    ranges of edges in the order of least members, large ones, so where near keys meet, an edge goes to few blocks; while a block
    would meet more than ``HELD`` members, they are made smaller, down to ``LEADS``."""
    cores, edges, leads = hg.edges.sparkSession.sparkContext.defaultParallelism, hg.edges.count(), NEAR
    while True:
        blocks = max(TASKS * cores, -(-edges // leads))
        laid = stage(hg.edges.repartitionByRange(blocks, F.col("members")[0], F.col("e")).select("e", "members", F.spark_partition_id().alias("b")))
        at = laid.select("e", "b", F.explode("members").alias("v"))
        into = stage(at.groupBy("v").agg(F.collect_set("b").alias("to"), F.count(F.lit(1)).alias("d")).where("d > 1"))
        held = into.select(F.explode("to").alias("b"), "d").groupBy("b").agg(F.sum("d").alias("d")).agg(F.max("d")).first()[0] or 0
        if held <= HELD or leads <= LEADS:
            break
        leads = max(LEADS, leads // 7)
    met = at.join(into.where(F.size("to") > 1), "v").groupBy("e").agg(F.array_distinct(F.flatten(F.collect_list("to"))).alias("to"))
    top = laid.agg(F.max(F.array_max("members")).alias("hi"), F.min(F.array_min("members")).alias("lo")).first()  # codes as INT where they fit
    codes = F.col("members").cast("array<int>") if top["hi"] is not None and top["lo"] >= -(2**31) and top["hi"] < 2**31 else F.col("members")
    dealt = laid.join(met, "e", "left").select(F.explode(F.coalesce(F.array_union("to", F.array(F.col("b"))), F.array(F.col("b")))).alias("to"), "e", codes.alias("codes"), "b")
    return dealt.select(F.col("to").alias("b"), F.col("e").alias("t"), "codes", (F.col("to") == F.col("b")).alias("lead")).repartition(max(blocks, min(8 * blocks, 1_000)), "b")  # few blocks a task


def as_types(table: pa.Table) -> pa.Table:
    """A block of near edges with the columns of types."""
    lists = table["codes"].combine_chunks()
    lists = lists if isinstance(lists, pa.ListArray) else pa.concat_arrays(lists.chunks)
    codes = pa.ListArray.from_arrays(pa.array(lists.offsets.to_numpy() - lists.offsets[0].as_py()), lists.flatten().dictionary_encode().indices)
    n, one = np.diff(codes.offsets.to_numpy()).astype(np.int64), np.ones(len(codes), np.int64)
    return pa.table({"t": table["t"], "codes": codes, "own": np.zeros(len(codes), np.int32), "m": one, "bound": n, "lead": table["lead"], "other": one.astype(bool)})


class _Block:
    """One block in arrays: types in order, the codes of each (CSR) and the types of each vertex (CSR)."""

    def __init__(self, table: pa.Table):
        order = np.lexsort((table["t"].to_numpy(), table["bound"].to_numpy()))
        table = table.take(pa.array(order)).combine_chunks()
        codes = table["codes"].combine_chunks()
        codes = codes if isinstance(codes, pa.ListArray) else pa.concat_arrays(codes.chunks)
        self.s, flat = np.diff(codes.offsets.to_numpy()).astype(np.int32), codes.flatten().to_numpy()
        self.t, self.m, self.count = table["t"].to_numpy(), table["m"].to_numpy(), len(order)
        self.lead, self.other = (table[c].to_numpy() for c in ("lead", "other"))
        self.n = self.s + table["own"].to_numpy().astype(np.int32)
        self.at = np.concatenate([[0], np.cumsum(self.s, dtype=np.int64)])
        there = np.zeros(int(flat.max(initial=-1)) + 1, bool)
        there[flat] = True
        self.v, self.vertices = (np.cumsum(there, dtype=np.int32) - np.int32(1))[flat], int(there.sum())
        del table, codes, flat
        owner = np.repeat(np.arange(self.count, dtype=np.int32), self.s)
        self.types = owner[np.argsort(self.v, kind="stable")]
        self.of = np.concatenate([[0], np.cumsum(np.bincount(self.v, minlength=self.vertices))])
        self.kind = np.int16 if self.n.max(initial=0) < 1 << 14 else np.int32  # of overlaps and of sums of two
        self.bits = self.whole = None

    def postings(self, i: int) -> list[np.ndarray]:
        return [self.types[self.of[v] : self.of[v + 1]] for v in self.v[self.at[i] : self.at[i + 1]]]

    def near(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Types that share a vertex with i (i itself too) and how many."""
        got = np.concatenate(self.postings(i))
        if len(got) * 8 > self.count:
            w = np.bincount(got, minlength=self.count)
            js = np.flatnonzero(w)
            return js, w[js]
        return np.unique(got, return_counts=True)

    def overlaps(self) -> None:
        """What comparisons of any two types read: bits of few vertices, or a matrix of few types."""
        if self.vertices <= BITS:
            word, bit = self.v >> 6, np.uint64(1) << (self.v & 63).astype(np.uint64)
            self.bits = np.zeros((max(1, -(-self.vertices // 64)), self.count), np.uint64)
            np.bitwise_or.at(self.bits, (word, np.repeat(np.arange(self.count), self.s)), bit)
        elif self.count <= MATRIX:
            self.whole = np.zeros((self.count, self.count), self.kind)
            for v in range(self.vertices):
                p = self.types[self.of[v] : self.of[v + 1]]
                self.whole[np.ix_(p, p)] += 1

    def beside(self, i: int, js: np.ndarray) -> np.ndarray:
        """Overlaps of the types js outside of i."""
        out = np.zeros((len(js), len(js)), self.kind)
        row = np.repeat(np.arange(len(js)), self.s[js])
        v = self.v[np.arange(len(row)) + np.repeat(self.at[js] - np.cumsum(self.s[js]) + self.s[js], self.s[js])]
        keep = ~np.isin(v, self.v[self.at[i] : self.at[i + 1]])
        v, row = v[keep], row[keep]
        order = np.argsort(v, kind="stable")
        v, row = v[order], row[order]
        cuts = np.flatnonzero(np.diff(v)) + 1
        starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(v)]])
        many = np.flatnonzero(ends - starts > 1)
        if len(many) * len(js) ** 2 <= 1 << 22 and len(many) > 4:
            hot = np.zeros((len(js), len(many)), np.float32)
            for c, x in enumerate(many):
                hot[row[starts[x] : ends[x]], c] = 1
            return (hot @ hot.T).astype(self.kind)
        for x in many:
            r = row[starts[x] : ends[x]]
            out[np.ix_(r, r)] += 1
        return out


def _signature(nest, g, pairs, solos) -> np.ndarray:
    u = np.uint8
    out = nest * u(32)
    out += (g > 0).view(u) * u(16)
    p = pairs[0].view(u) + pairs[1].view(u)
    p += pairs[2].view(u)
    out += p * u(4)
    for s in solos:
        out += s.view(u)
    return out


def _led(block: _Block, i: int, js: np.ndarray, w: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(first row, signatures of rows x later types from that row on) for the pairs of types js after i; w: overlaps with i."""
    if len(js) < 2:
        return
    n, ni, a = block.n[js].astype(block.kind), block.kind(block.n[i]), w.astype(block.kind)
    near_i = (a == np.minimum(ni, n)).view(np.uint8)
    rest = n - a
    members = block.postings(i)
    if len(members) <= 64:
        kind = next(k for k, most in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.uint64, 64)) if len(members) <= most)
        mine = np.zeros(block.count, kind)
        for p, types in enumerate(members):
            mine[types] |= kind(1 << p)
        mine = mine[js]
    else:
        mine = np.zeros((len(members), block.count), np.float32)
        for p, types in enumerate(members):
            mine[p, types] = 1
        mine = np.ascontiguousarray(mine[:, js])
    beside = None if block.bits is not None or block.whole is not None else block.beside(i, js)
    words = None if block.bits is None else block.bits[:, js]
    d, at = len(js), 0
    while at < d - 1:
        to = min(d, at + max(1, CELLS // (d - at)))
        r, c = slice(at, to), slice(at, d)
        g = (np.bitwise_count(mine[r, None] & mine[None, c]) if mine.ndim == 1 else mine[:, r].T @ mine[:, c]).astype(block.kind)
        if words is not None:
            x = np.bitwise_count(words[0, r, None] & words[0, None, c]).astype(block.kind)
            for k in range(1, len(words)):
                x += np.bitwise_count(words[k, r, None] & words[k, None, c])
        elif beside is not None:
            x = beside[r, c] + g
        else:
            x = block.whole[js[r, None], js[None, c]]
        nest = (x == np.minimum(n[r, None], n[None, c])).view(np.uint8)
        nest += near_i[r, None]
        nest += near_i[None, c]
        pairs = (a[r, None] > g, a[None, c] > g, x > g)
        over = x - g
        sig = _signature(nest, g, pairs, (g + ni > a[r, None] + a[None, c], rest[r, None] > over, rest[None, c] > over))
        sig[x == 0] = _OPEN
        rows = to - at
        sig[:, :rows][np.tri(rows, dtype=bool)] = _OPEN  # each pair once
        yield at, sig
        at = to


def _twins(block: _Block, a: np.ndarray | int, b: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Signatures of two edges of type a and one of type b.  Two edges of a type have private vertices."""
    sa, nb = block.s[a], block.n[b]
    nest = np.uint8(2) * (w == nb).view(np.uint8)  # b in both; neither of them lies in anything
    none = np.zeros(len(w), bool)
    always = np.ones(len(w), bool)
    return _signature(nest, w, (np.broadcast_to(sa > w, w.shape).copy(), none, none), (always, always, nb > w))


def _tally(into: Counter, sig: np.ndarray, weight: np.ndarray | None = None) -> None:
    if weight is None and sig.size % 2 == 0 and sig.size > 1 << 12:
        pairs = np.bincount(np.ascontiguousarray(sig).ravel().view(np.uint16), minlength=1 << 16).reshape(256, 256)
        got = pairs.sum(0) + pairs.sum(1)
    else:
        got = np.bincount(sig.ravel(), None if weight is None else weight.ravel(), minlength=256)
    for s in np.flatnonzero(got):
        if s != _OPEN:
            into[int(s)] += int(got[s])


def _around(table: pa.Table) -> pa.Table:
    """(t, d, w): linked edges of an edge of each leading type and overlaps with them, as far as this slice holds them."""
    block = _Block(table)
    m, rows = np.where(block.other, block.m, 0), []
    for i in np.flatnonzero(block.lead):
        js, w = block.near(i)
        itself = int(block.other[i])
        rows.append((int(block.t[i]), int(m[js].sum()) - itself, int((m[js] * w).sum()) - itself * int(block.s[i])))
    t, d, w = zip(*rows) if rows else ((), (), ())
    return pa.table({"t": pa.array(t, pa.int64()), "d": pa.array(d, pa.int64()), "w": pa.array(w, pa.int64())})


def _census(table: pa.Table) -> pa.Table:
    """(key, cnt): triads by pattern; links, their overlaps and pairs of linked edges around one edge by name."""
    block, found, figures = _Block(table), Counter(), Counter()
    single = bool((block.m == 1).all())
    block.overlaps()
    for i in np.flatnonzero(block.lead):
        js, w = block.near(i)
        m, mi = block.m[js], int(block.m[i])
        degree = int(m.sum()) - 1
        figures["two_hop"] += mi * (degree * (degree - 1) // 2)
        later = js > i
        js, w, m = js[later], w[later], m[later]
        twice = mi * (mi - 1) // 2
        figures["links"] += mi * int(m.sum()) + twice
        figures["overlaps"] += mi * int((m * w).sum()) + twice * int(block.s[i])
        got = Counter()
        for at, sig in _led(block, i, js, w):
            rows = m[at : at + len(sig)]
            _tally(got, sig, None if single else (rows[:, None] * m[None, at:]).astype(np.float64))
        for s, x in got.items():
            found[s] += x * mi
        if single:
            continue
        if mi > 1:
            _tally_twins(found, _twins(block, i, js, w), m, twice)
            found[16 + 3] += mi * (mi - 1) * (mi - 2) // 6
        more = m > 1
        if more.any():
            _tally_twins(found, _twins(block, js[more], np.full(int(more.sum()), i), w[more]), m[more] * (m[more] - 1) // 2, mi)
    rows = [(str(_BY_SIGNATURE[s]), n) for s, n in found.items() if n] + list(figures.items())
    return pa.table({"key": pa.array([k for k, _ in rows], pa.string()), "cnt": pa.array([n for _, n in rows], pa.int64())})


def _tally_twins(found: Counter, sig: np.ndarray, m: np.ndarray, times: int) -> None:
    for s in np.unique(sig):
        found[int(s)] += int(m[sig == s].sum()) * times


def _per_edge(table: pa.Table, patterns: tuple[int, ...]) -> pa.Table:
    """(t, pattern, cnt): triads of the patterns that an edge of type t takes part in, those led by this block."""
    block = _Block(table)
    block.overlaps()
    wanted = {s: p for s, p in _BY_SIGNATURE.items() if p in patterns}
    out = {s: np.zeros(block.count, np.int64) for s in wanted}
    for i in np.flatnonzero(block.lead):
        js, w = block.near(i)
        js, w = js[js > i], w[js > i]
        m, mi = block.m[js], int(block.m[i])
        for at, sig in _led(block, i, js, w):
            rows, cols, r = js[at : at + len(sig)], js[at:], m[at : at + len(sig)].astype(np.float64)
            for s in wanted:
                if (hit := sig == s).any():
                    right = (hit @ m[at:].astype(np.float64)).astype(np.int64)
                    out[s][rows] += mi * right
                    out[s][cols] += mi * (r @ hit).astype(np.int64)
                    out[s][i] += int((right * m[at : at + len(sig)]).sum())
        twos = [(np.full(len(js), i), js, _twins(block, i, js, w))] if mi > 1 else []
        if (more := m > 1).any():
            twos.append((js[more], np.full(int(more.sum()), i), _twins(block, js[more], np.full(int(more.sum()), i), w[more])))
        for a, b, sig in twos:
            for s in wanted:
                x, y = a[sig == s], b[sig == s]
                np.add.at(out[s], x, (block.m[x] - 1) * block.m[y])
                np.add.at(out[s], y, block.m[x] * (block.m[x] - 1) // 2)
        if 16 + 3 in wanted:
            out[16 + 3][i] += (mi - 1) * (mi - 2) // 2
    rows = [(block.t[at], np.full(len(at), wanted[s]), c[at]) for s, c in out.items() if len(at := np.flatnonzero(c))]
    t, p, c = (np.concatenate(x) for x in zip(*rows)) if rows else (np.zeros(0, np.int64),) * 3
    return pa.table({"t": pa.array(t, pa.int64()), "pattern": pa.array(p, pa.int32()), "cnt": pa.array(c, pa.int64())})


def census(hg: Hypergraph) -> DataFrame:
    """(key, cnt): ``links``, ``overlaps`` (their shared vertices in all), ``two_hop`` (pairs of neighbours of an edge), and the
    triads of each pattern under its number; keys of no count are left out."""
    types, _ = edge_types(hg)
    got = _dealt(types).groupBy("b").applyInArrow(_census, "key string, cnt long")
    return stage(got.groupBy("key").agg(F.sum("cnt").alias("cnt")))


def link_figures(hg: Hypergraph) -> DataFrame:
    """(links, overlaps, two_hop) of a census as one row, without a triad looked at; null sums where there is no link."""
    types, _ = edge_types(hg)
    got = _dealt(types, sliced=True).groupBy("b", "s").applyInArrow(_around, "t long, d long, w long").groupBy("t").agg(F.sum("d").alias("d"), F.sum("w").alias("w"))
    row = got.join(types.select("t", "m"), "t").where("d > 0").agg(F.coalesce(F.expr("sum(m * d) div 2"), F.lit(0)).alias("links"), F.expr("sum(m * w) div 2").alias("overlaps"), F.sum(F.expr("m * (d * (d - 1) div 2)")).alias("two_hop"))
    return stage(row)


def triad_counts(found: DataFrame) -> DataFrame:
    """(pattern, cnt) of a census."""
    return found.where("key NOT IN ('links', 'overlaps', 'two_hop')").select(F.col("key").cast("int").alias("pattern"), "cnt")


def figure(found: DataFrame, key: str) -> DataFrame:
    """One figure of a census as a single row, 0 if there is none."""
    return found.agg(F.coalesce(F.sum(F.when(F.col("key") == key, F.col("cnt"))), F.lit(0)).alias(key))


def triads_per_edge(hg: Hypergraph, patterns: tuple[int, ...]) -> DataFrame:
    """(e, pattern, cnt): triads of the patterns an edge takes part in."""
    types, edges = edge_types(hg)
    got = _dealt(types).groupBy("b").applyInArrow(lambda table: _per_edge(table, patterns), "t long, pattern int, cnt long")
    of = got.groupBy("t", "pattern").agg(F.sum("cnt").alias("cnt")).join(types.select("t", "codes", "own"), "t")
    return edges.join(of, ["codes", "own"]).select("e", "pattern", "cnt")
