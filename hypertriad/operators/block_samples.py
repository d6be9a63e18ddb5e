"""Samples of links without a table of links, for inputs whose links outgrow the disk or the time to write them.

Links are formed in the blocks of ``blocks.dealt_near``, each at its lesser edge, and only counted and drawn from: a block
hands on its rows of least key, never more than the sample asks for.  The sampled links then go to all edges, as triads of a
link need no more than the link's two edges and a third one.  Draws and estimates are those of ``sampling``.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..model import Hypergraph, dictionary_encode
from ..stages import stage
from .blocks import _BY_SIGNATURE, TASKS, _Block, _signature, as_types, dealt_near

#: Edges of a partition that sampled links are held against.
PART = 1_000_000
_FAMILY_KINDS = {"TTT": "T", "TCC": "T", "CCC": "C", "TTC": "C"}


@dataclass(frozen=True)
class LinksInBlocks:
    """The links of a hypergraph as samplers read them, in place of a table."""

    hg: Hypergraph

    def numbered(self) -> Hypergraph:
        """The hypergraph with BIGINT vertices."""
        if isinstance(self.hg.incidence.schema["v"].dataType, LongType):
            return self.hg
        inc = dictionary_encode(self.hg.incidence, "v", "code").select("e", F.col("code").alias("v"))
        edges = stage(inc.groupBy("e").agg(F.sort_array(F.collect_list("v")).alias("members")).select("e", F.size("members").alias("n"), "members"))
        return Hypergraph(edges.select("e", F.explode("members").alias("v")), edges)

    def drawn(self, alpha: int, seed: int, hg: Hypergraph) -> tuple[dict[str, int], DataFrame]:
        """Links of each kind, and (kind, i, j, key) of the links of least key, ``alpha`` of each kind at least where there are."""
        got = stage(dealt_near(hg).groupBy("b").applyInArrow(lambda table: _drawn(table, alpha, seed), "kind string, cnt long, i long, j long, key binary"))
        sizes = {r["kind"]: r["n"] for r in got.where("key IS NULL").groupBy("kind").agg(F.sum("cnt").alias("n")).collect()}  # two rows
        return sizes, got.where("key IS NOT NULL").select("kind", "i", "j", "key")

    def by_link(self, alpha: int, seed: int = 0) -> tuple[DataFrame, float]:
        """(pattern, mult) of the triads of which a sampled link is the one of least order, and what each stands for."""
        hg = self.numbered()
        sizes, links = self.drawn(alpha, seed, hg)
        n = sum(sizes.values())
        lead = links.orderBy("key", "i", "j").limit(alpha).select("i", "j").collect()  # alpha rows at most
        return _triads(hg, [("any", r["i"], r["j"]) for r in lead]), n / max(1, min(alpha, n))

    def by_family(self, alpha: int, seed: int, share_of) -> tuple[DataFrame, dict[str, int], dict[str, int]]:
        """(pattern, mult) of the triads led by a sampled link of their family's pool, pools and shares by family.  share_of: the
        shares of t cross links and c nest links."""
        hg = self.numbered()
        sizes, links = self.drawn(alpha + 1, seed, hg)  # a share is rounded, and one at least
        pool = {f: sizes.get(kind, 0) for f, kind in _FAMILY_KINDS.items()}
        share, lead = share_of(pool["TTT"], pool["CCC"]), []
        for f, kind in _FAMILY_KINDS.items():
            if share.get(f):
                lead += [(f, r["i"], r["j"]) for r in links.where(F.col("kind") == kind).orderBy("key", "i", "j").limit(share[f]).collect()]
        return _triads(hg, lead), pool, share


def _drawn(table: pa.Table, alpha: int, seed: int) -> pa.Table:
    """Numbers of links by kind (key null), and those of the least keys of each kind; a link counts where its lesser edge leads."""
    block = _Block(as_types(table))
    tail = f":{seed}".encode()
    names = [b"%d" % e for e in block.t.tolist()]
    count, kept, most = Counter(), {"T": [], "C": []}, {"T": b"\xff" * 17, "C": b"\xff" * 17}
    for i in np.flatnonzero(block.lead):
        js, w = block.near(i)
        after = block.t[js] > block.t[i]
        js, w = js[after], w[after]
        nest, head = w == np.minimum(block.n[js], block.n[i]), names[i] + b","
        for kind, some in (("T", js[~nest]), ("C", js[nest])):
            count[kind] += len(some)
            mine, bar = kept[kind], most[kind]
            mine += [(d, i, j) for j in some.tolist() if (d := hashlib.md5(head + names[j] + tail).digest()) <= bar]
            if len(mine) > 4 * alpha + 1_000:
                mine.sort(key=lambda r: (r[0], block.t[r[1]], block.t[r[2]]))
                del mine[alpha:]
                most[kind] = mine[-1][0] if mine else b""
    rows = [(kind, n, None, None, None) for kind, n in count.items() if n]
    for kind, mine in kept.items():
        mine.sort(key=lambda r: (r[0], block.t[r[1]], block.t[r[2]]))
        rows += [(kind, 1, int(block.t[i]), int(block.t[j]), d) for d, i, j in mine[:alpha]]
    kind, n, i, j, key = zip(*rows) if rows else ((),) * 5
    return pa.table({"kind": pa.array(kind, pa.string()), "cnt": pa.array(n, pa.int64()), "i": pa.array(i, pa.int64()), "j": pa.array(j, pa.int64()), "key": pa.array(key, pa.binary())})


def _triads(hg: Hypergraph, lead: list[tuple[str, int, int]]) -> DataFrame:
    """(pattern, mult) of the triads that the links ``lead`` (rule, i, j) form with any third edge; the rule is a family or any."""
    spark = hg.edges.sparkSession
    ids = sorted({x for _, *link in lead for x in link})
    held = spark.createDataFrame([(x,) for x in ids], "e long")
    members = {r["e"]: np.array(r["members"], np.int64) for r in hg.edges.join(F.broadcast(held), "e").select("e", "members").collect()}  # two edges for each sampled link
    parts = max(TASKS * spark.sparkContext.defaultParallelism, -(-hg.edges.count() // PART))
    rows = hg.edges.select("e", "members").repartition(parts, "e").mapInArrow(lambda batches: _thirds(batches, lead, members), "pattern int, mult long")
    return stage(rows.groupBy("pattern").agg(F.sum("mult").alias("mult")))


def _thirds(batches: Iterator[pa.RecordBatch], lead: list[tuple[str, int, int]], members: dict[int, np.ndarray]) -> Iterator[pa.RecordBatch]:
    batches = [b for b in batches if b.num_rows]
    if not batches:
        return
    table = pa.Table.from_batches(batches).combine_chunks()
    lists = table["members"].combine_chunks()
    lists = lists if isinstance(lists, pa.ListArray) else pa.concat_arrays(lists.chunks)
    ids, n, flat = table["e"].to_numpy(), np.diff(lists.offsets.to_numpy()).astype(np.int64), lists.flatten().to_numpy()
    order = np.argsort(flat, kind="stable")
    vertices, starts = np.unique(flat[order], return_index=True)
    owner, ends = np.repeat(np.arange(len(ids)), n)[order], np.append(starts[1:], len(flat))

    def met(m: np.ndarray) -> np.ndarray:
        """The edges at the vertices m, once for each."""
        at = np.searchsorted(vertices, m)
        at = at[(at < len(vertices)) & (vertices[np.minimum(at, len(vertices) - 1)] == m)]
        return np.concatenate([owner[starts[k] : ends[k]] for k in at]) if len(at) else owner[:0]

    found, seen, many = Counter(), {}, np.zeros(len(ids), np.int64)
    for rule, i, j in lead:
        if len(seen) > 256:
            seen.clear()
        for x in {i, j} - seen.keys():
            seen[x] = np.unique(met(members[x]), return_counts=True)
        (ki, wi), (kj, wj) = seen[i], seen[j]
        third, a, b = np.intersect1d(ki, kj, assume_unique=True, return_indices=True)
        wik, wjk, e = wi[a], wj[b], ids[third]
        here = (e != i) & (e != j)
        shared = np.intersect1d(members[i], members[j], assume_unique=True)
        ni, nj, nk, w = len(members[i]), len(members[j]), n[third], len(shared)
        nest_i, nest_j = wik == np.minimum(ni, nk), wjk == np.minimum(nj, nk)
        if rule in ("any", "TTT"):
            here &= e > max(i, j)
        if rule in ("TTT", "TTC"):
            here &= ~nest_i & ~nest_j
        elif rule == "TCC":
            here &= nest_i & nest_j
        elif rule == "CCC":
            here &= nest_i & nest_j & (nk < min(ni, nj))
        if not here.any():
            continue
        common = met(shared)
        np.add.at(many, common, 1)
        third, wik, wjk, nk, nest_i, nest_j = (x[here] for x in (third, wik, wjk, nk, nest_i, nest_j))
        g = many[third]
        many[common] = 0
        nests = nest_i.astype(np.uint8) + nest_j.astype(np.uint8) + np.uint8(w == min(ni, nj))
        sig = _signature(nests, g, (w > g, wik > g, wjk > g), (ni - w - wik + g > 0, nj - w - wjk + g > 0, nk - wik - wjk + g > 0))
        for s, c in zip(*np.unique(sig, return_counts=True)):
            found[_BY_SIGNATURE[int(s)]] += int(c)
    if found:
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int32()), pa.array(list(found.values()), pa.int64())], ["pattern", "mult"])
