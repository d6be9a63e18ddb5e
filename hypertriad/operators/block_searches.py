"""The exact searches inside the blocks of ``blocks``: each method finds its triads in its own way around the edges a task leads,
in memory, so that neither links nor lead pairs are written or exchanged.  A block is dealt once for all methods.

Methods compare edges, not types: a type of several edges is repeated.  Searches of three cross links are led by the edge that
is first in the order of sizes, those of nest links by the edge that both nest links share, or by the lesser of the only one.
Blocks of many small edges are searched by ``sparse_searches``, many leading edges at once.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..model import Hypergraph
from ..stages import stage
from . import blocks, sparse_searches
from .blocks import _BY_SIGNATURE, _OPEN, CELLS, _Block, _census, _dealt, _led, _signature, _tally, as_types, dealt_near, edge_types

#: Pairs of edges for each meeting of two at a vertex, from which on edges are sparse.
SPARSE = 20
#: Share of meeting pairs of neighbours from which on all pairs of a block are compared as matrices.
DENSE = 0.3

#: Signature of each pattern, as counts are kept by signature.
_SIGNATURE = {p: s for s, p in _BY_SIGNATURE.items()}


class _Edges(_Block):
    """A block in which every edge stands for itself, in the order of sizes."""

    def __init__(self, table: pa.Table):
        m = table["m"].to_numpy()
        sizes = pc.add(pc.list_value_length(table["codes"]).cast(pa.int64()), table["own"].cast(pa.int64()))
        table = table.set_column(table.column_names.index("bound"), "bound", sizes)
        super().__init__(table.take(pa.array(np.repeat(np.arange(len(m)), m))) if (m > 1).any() else table)
        self.overlaps()
        self.mark = np.full(self.vertices, -1, np.int32)

    def held(self, js: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, vertex) of the edges js."""
        s = self.s[js]
        row = np.repeat(np.arange(len(js)), s)
        return row, self.v[np.arange(len(row)) + np.repeat(self.at[js] - np.cumsum(s) + s, s)]

    def meet(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Overlaps of the edges a (rows) with the edges b (columns)."""
        if self.whole is not None:
            return self.whole[a[:, None], b[None]]
        if self.bits is not None:
            out = np.bitwise_count(self.bits[0, a][:, None] & self.bits[0, b][None]).astype(self.kind)
            for word in self.bits[1:]:
                out += np.bitwise_count(word[a][:, None] & word[b][None])
            return out
        (ra, va), (rb, vb) = self.held(a), self.held(b)
        seen = np.unique(va)
        self.mark[seen] = np.arange(len(seen), dtype=np.int32)
        left, right = np.zeros((len(a), len(seen)), np.float32), np.zeros((len(b), len(seen)), np.float32)
        left[ra, self.mark[va]] = 1
        cols = self.mark[vb]
        both = cols >= 0
        right[rb[both], cols[both]] = 1
        self.mark[seen] = -1
        return (left @ right.T).astype(self.kind)


class _Links:
    """The links of edge i: others, overlaps and sizes, those of them that cross it and come later, and the edges it nests with."""

    def __init__(self, block: _Edges, i: int):
        js, w = block.near(i)
        other = js != i
        self.i, self.js, self.w = i, js[other], w[other].astype(block.kind)
        self.ni, self.n = block.kind(block.n[i]), block.n[self.js].astype(block.kind)
        self.nested = self.w == np.minimum(self.n, self.ni)
        self.up, self.down = self.js[self.nested & (self.n > self.ni)], self.js[self.nested & (self.n < self.ni)]
        self.later = self.js > i
        self.crossing = self.later & ~self.nested

    def shared(self, block: _Edges, at: np.ndarray) -> list[np.ndarray]:
        """The shared sets of the links at ``at`` as bits, a word for up to 64 members of i."""
        members, words = block.postings(self.i), []
        for k in range(0, len(members), 64):
            some = members[k : k + 64]
            kind = next(x for x, most in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.uint64, 64)) if len(some) <= most)
            word = np.zeros(block.count, kind)
            for p, edges in enumerate(some):
                word[edges] |= kind(1 << p)
            words.append(word[self.js[at]])
        return words


def _common(words: list[np.ndarray], r: slice, c: slice, kind: type) -> np.ndarray:
    """Sizes of the intersections of the shared sets r with the shared sets c."""
    out = np.bitwise_count(words[0][r, None] & words[0][None, c]).astype(kind)
    for word in words[1:]:
        out += np.bitwise_count(word[r, None] & word[None, c])
    return out


def _rows(d: int, cells: int = CELLS) -> Iterator[tuple[slice, slice]]:
    """Pairs of d things as blocks of a matrix: rows, and the columns from the first of them on."""
    at = 0
    while at < d - 1:
        to = min(d, at + max(1, cells // (d - at)))
        yield slice(at, to), slice(at, d)
        at = to


def _once(sig: np.ndarray) -> np.ndarray:
    """Signatures of a block of pairs, those of the same or the reversed pair taken out."""
    k = len(sig)
    sig[:, :k][np.tri(k, dtype=bool)] = _OPEN
    return sig


def _baseline(block: _Edges, at: _Links, found: Counter) -> None:
    """Every pair of later neighbours, connected or not; the connected ones by their seven regions."""
    js, w, n, ni = at.js[at.later], at.w[at.later], at.n[at.later], at.ni
    words = at.shared(block, at.later)
    for r, c in _rows(len(js)):
        g, x = _common(words, r, c, block.kind), block.meet(js[r], js[c])
        wr, wc, nr, nc = w[r, None], w[None, c], n[r, None], n[None, c]
        nests = (wr == np.minimum(ni, nr)).view(np.uint8) + (wc == np.minimum(ni, nc)).view(np.uint8) + (x == np.minimum(nr, nc)).view(np.uint8)
        sig = _signature(nests, g, (wr - g > 0, wc - g > 0, x - g > 0), (ni - wr - wc + g > 0, nr - wr - x + g > 0, nc - wc - x + g > 0))
        sig[x == 0] = _OPEN
        _tally(found, _once(sig))


def _nest_chain(block: _Edges, at: _Links, found: Counter) -> None:
    """Supersets times subsets of the middle edge, without forming a chain."""
    found[_SIGNATURE[1]] += len(at.up) * len(at.down)


def _nest_chain_enumerated(block: _Edges, at: _Links, found: Counter) -> None:
    """Every chain formed: each superset of the middle edge with each subset."""
    if len(at.down):
        step = max(1, CELLS // len(at.down))
        for k in range(0, len(at.up), step):
            big = at.up[k : k + step]
            chains = np.column_stack([np.repeat(big, len(at.down)), np.tile(at.down, len(big))])
            found[_SIGNATURE[1]] += len(chains)


def _two_nests(block: _Edges, at: _Links, found: Counter) -> None:
    """Pairs of supersets of an edge, and pairs of its subsets, that cross."""
    for js, yes, no in ((at.up, 2, 3), (at.down, 4, 5)):
        n = block.n[js].astype(block.kind)
        for r, c in _rows(len(js)):
            x, nr, nc = block.meet(js[r], js[c]), n[r, None], n[None, c]
            here = x == at.ni if yes == 2 else nr + nc - x == at.ni
            sig = np.where(here, np.uint8(_SIGNATURE[yes]), np.uint8(_SIGNATURE[no]))
            sig[(x == 0) | (x == np.minimum(nr, nc))] = _OPEN
            _tally(found, _once(sig))


def _one_nest(block: _Edges, at: _Links, found: Counter) -> None:
    """Supersets of an edge with the edges that cross both."""
    cross = ~at.nested
    third, w, n = at.js[cross], at.w[cross], at.n[cross]
    if not len(third):
        return
    step = max(1, CELLS // len(third))
    for k in range(0, len(at.up), step):
        big = at.up[k : k + step]
        x, nb = block.meet(big, third), block.n[big].astype(block.kind)[:, None]
        sig = np.where(x == w, np.uint8(_SIGNATURE[6]), np.where(at.ni + x - w == nb, np.uint8(_SIGNATURE[7]), np.uint8(_SIGNATURE[8])))
        sig[x == np.minimum(nb, n)] = _OPEN
        _tally(found, sig)


def _cross(block: _Edges, at: _Links, found: Counter) -> None:
    """Pairs of later cross links, their shared sets intersected, closed by a cross link."""
    js, w, n = at.js[at.crossing], at.w[at.crossing], at.n[at.crossing]
    if len(js) < 2:
        return
    words, rest = at.shared(block, at.crossing), n - w
    for r, c in _rows(len(js)):
        g, x = _common(words, r, c, block.kind), block.meet(js[r], js[c])
        over = x - g
        sig = _signature(np.uint8(0), g, (w[r, None] > g, w[None, c] > g, over > 0), (g + at.ni > w[r, None] + w[None, c], rest[r, None] > over, rest[None, c] > over))
        sig[(x == 0) | (x == np.minimum(n[r, None], n[None, c]))] = _OPEN
        _tally(found, _once(sig))


def _closed(block: _Edges, at: _Links, r: slice, c: slice, g: np.ndarray, found: Counter) -> None:
    """Counts the pairs of crossing links with a common part (g, rows r and columns c) that a cross link closes."""
    js, w, n = at.js[at.crossing], at.w[at.crossing], at.n[at.crossing]
    a, b = np.nonzero(g)
    after = b > a
    a, b = a[after], b[after]
    if not len(a):
        return
    g, j, k = g[a, b], a + r.start, b + c.start
    x = block.whole[js[j], js[k]] if block.whole is not None else block.meet(js[r], js[c])[a, b]
    crossing = x < np.minimum(n[j], n[k])  # they share the common part
    g, x, j, k = g[crossing], x[crossing], j[crossing], k[crossing]
    wj, wk, nj, nk = w[j], w[k], n[j], n[k]
    sig = _signature(np.zeros(len(g), np.uint8), g, (wj > g, wk > g, x > g), (at.ni + g > wj + wk, nj + g > wj + x, nk + g > wk + x))
    _tally(found, sig)


def _core_vertex(block: _Edges, at: _Links, found: Counter) -> None:
    """Pairs of later cross links that meet at a vertex of the leading edge, by the number of their meetings."""
    js = at.js[at.crossing]
    if len(js) < 2:
        return
    place = np.full(block.count, -1, np.int64)
    place[js] = np.arange(len(js))
    met = [p[p >= 0] for p in (place[edges] for edges in block.postings(at.i))]
    for r, c in _rows(len(js), 16 * CELLS):
        g = np.zeros((r.stop - r.start, c.stop - c.start), block.kind)
        for p in met:
            lo, hi = np.searchsorted(p, (r.start, r.stop))
            if hi > lo:
                g[np.ix_(p[lo:hi] - r.start, p[lo:] - c.start)] += 1
        _closed(block, at, r, c, g, found)


def _core_grouped(block: _Edges, at: _Links, found: Counter) -> None:
    """Later cross links of equal shared sets are a group; a pair of groups is intersected once."""
    js = at.js[at.crossing]
    if len(js) < 2:
        return
    sets = np.stack([x.astype(np.uint64) for x in at.shared(block, at.crossing)], 1)
    groups, of = np.unique(sets, axis=0, return_inverse=True) if sets.shape[1] > 1 else np.unique(sets[:, 0], return_inverse=True)
    words, of = list(groups.reshape(len(groups), -1).T), of.ravel()
    for r, c in _rows(len(js), 16 * CELLS):
        own, mine = np.unique(of[r], return_inverse=True)
        pairs = np.concatenate([_common(words, own[k : k + 64], slice(None), block.kind) for k in range(0, len(own), 64)])
        _closed(block, at, r, c, pairs[mine[:, None], of[None, c]], found)


def _coreless(block: _Edges, at: _Links, found: Counter) -> None:
    """Pairs of later cross links with disjoint shared sets, closed by a cross link; each edge must hold two overlaps."""
    two = at.crossing & (at.n >= 2)
    js, w, n = at.js[two], at.w[two], at.n[two]
    if at.ni < 2 or len(js) < 2:
        return
    words = at.shared(block, two)
    for r, c in _rows(len(js)):
        apart = (words[0][r, None] & words[0][None, c]) == 0
        for word in words[1:]:
            apart &= (word[r, None] & word[None, c]) == 0
        x = block.meet(js[r], js[c])
        sig = np.uint8(12) + (at.ni > w[r, None] + w[None, c]).view(np.uint8)  # three regions of two
        sig += ((n - w)[r, None] > x).view(np.uint8)
        sig += ((n - w)[None, c] > x).view(np.uint8)
        sig[~apart | (x == 0) | (x == np.minimum(n[r, None], n[None, c]))] = _OPEN
        _tally(found, _once(sig))


def _each(block: _Edges, at: _Links, found: Counter) -> None:
    """Pairs of later links of any kind, by their seven regions."""
    for _, sig in _led(block, at.i, at.js[at.later], at.w[at.later]):
        _tally(found, sig)


SEARCHES: dict[str, Callable[[_Edges, _Links, Counter], None]] = {
    "baseline": _baseline, "nest_chain": _nest_chain, "nest_chain_enumerated": _nest_chain_enumerated, "two_nests": _two_nests, "one_nest": _one_nest,
    "cross": _cross, "core_vertex": _core_vertex, "core_grouped": _core_grouped, "coreless": _coreless,
}


def _closing(block: _Edges) -> float:
    """Share of the pairs of later neighbours that meet, around some of the leading edges; it decides the way, not the counts."""
    leads, pairs, met = np.flatnonzero(block.lead), 0, 0
    for i in leads[:: max(1, len(leads) // 8)]:
        js, w = block.near(i)
        later = js > i
        for _, sig in _led(block, i, js[later], w[later]):
            met += int((sig != _OPEN).sum())
        pairs += int(later.sum()) * (int(later.sum()) - 1) // 2
    return met / max(1, pairs)


def _searched(table: pa.Table, names: tuple[str, ...]) -> pa.Table:
    """(method, pattern, cnt) of the triads that this block's edges lead; ``all`` is its census."""
    table = table if "m" in table.column_names else as_types(table)
    block, found = _Edges(table), {name: Counter() for name in names}
    sparse = block.bits is None and block.whole is None and not (names == ("all",) and _closing(block) > DENSE)
    batched = tuple(name for name in names if sparse and name in sparse_searches.BATCHED)
    rest = sparse_searches.search(block, batched, _SIGNATURE, found) if batched else ()
    rows = [("all", int(r["key"]), r["cnt"]) for r in _census(table).to_pylist() if r["key"].isdigit()] if "all" in names and not sparse else []
    searches = {name: _each if name == "all" else SEARCHES[name] for name in names if sparse or name != "all"}
    for leads, named in ((rest, batched), (np.flatnonzero(block.lead), [name for name in searches if name not in batched])):
        for i in leads if named else ():
            links = _Links(block, i)
            for name in named:
                searches[name](block, links, found[name])
    rows += [(name, _BY_SIGNATURE[s], n) for name, counts in found.items() for s, n in counts.items() if n]
    return pa.table({"method": pa.array([r[0] for r in rows], pa.string()), "pattern": pa.array([r[1] for r in rows], pa.int32()), "cnt": pa.array([r[2] for r in rows], pa.int64())})


def is_sparse(hg: Hypergraph) -> bool:
    """Whether edges on numbered vertices are many and meet few others each: then fewer are dealt as near edges than as types."""
    if not isinstance(hg.incidence.schema["v"].dataType, LongType) or (edges := hg.edges.count()) <= blocks.MATRIX:
        return False
    met = hg.incidence.groupBy("v").agg(F.count(F.lit(1)).alias("d")).agg(F.sum(F.col("d") * F.col("d"))).first()[0]
    return met * SPARSE <= edges * edges


def counted(hg: Hypergraph) -> DataFrame:
    """(pattern, cnt) of all triads, without a table of links: by the search of near edges where they are sparse, else by types."""
    if not is_sparse(hg):
        return blocks.triad_counts(blocks.census(hg))
    return searched(hg, ("all",)).select("pattern", "cnt")


def searched(hg: Hypergraph, names: tuple[str, ...] = (*SEARCHES, "all")) -> DataFrame:
    """(method, pattern, cnt) of each named method; patterns it found none of are left out.  Many edges on numbered vertices are
    dealt in blocks of near ones, others as types."""
    if unknown := set(names) - {*SEARCHES, "all"}:
        raise ValueError(f"unknown methods {sorted(unknown)}")
    near = isinstance(hg.incidence.schema["v"].dataType, LongType) and hg.edges.count() > blocks.MATRIX
    laid = dealt_near(hg) if near else _dealt(edge_types(hg)[0])
    got = laid.groupBy("b").applyInArrow(lambda table: _searched(table, names), "method string, pattern int, cnt long")
    return stage(got.groupBy("method", "pattern").agg(F.sum("cnt").alias("cnt")))
