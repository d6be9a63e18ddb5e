"""The exact searches of ``block_searches`` for blocks of many small edges, for many leading edges at once.

An edge meets few others at each of its vertices, so most pairs of its neighbours share nothing and are never looked at: pairs
come from the meetings at the vertices of the leading edge, and from the few vertices outside of it that two neighbours share.
Edges are in the order of their sizes, so supersets of an edge come after it and its subsets before.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np

from .blocks import _OPEN, _signature, _tally

#: Pairs compared at once, meetings and marks (leading edges times vertices) of one batch of leading edges.
PAIRS = 1 << 16
MEETINGS = 1 << 18
MARKS = 1 << 25
#: Kinds of pairs of links up to which pairs are counted by kind.
KINDS = 1 << 18
#: Pairs at its vertices and members up to which an edge is led in a batch.
MOST_PAIRS = 1 << 24
MEMBERS = 64

_LINK = 31  # bits of a link's number


def _from(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each of the starts, as many as its size."""
    ends = np.cumsum(sizes)
    out = np.repeat(starts - ends + sizes, sizes)
    out += np.arange(len(out))
    return out


def _pieces(cost: np.ndarray, most: int) -> Iterator[slice]:
    """Consecutive slices of at most that cost, one thing at least in each."""
    total, at = np.cumsum(cost), 0
    while at < len(cost):
        to = max(at + 1, int(np.searchsorted(total, most + (total[at - 1] if at else 0), "right")))
        yield slice(at, to)
        at = to


def _later(group: np.ndarray) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
    """Pairs within the runs of equal values, in pieces: first places, how many second ones each has, and these."""
    ends = np.append(np.flatnonzero(group[1:] != group[:-1]) + 1, len(group)) if len(group) else np.zeros(0, np.int64)
    after = np.repeat(ends, np.diff(ends, prepend=0)) - np.arange(len(group)) - 1
    for piece in _pieces(after, PAIRS):
        if (many := after[piece]).any():
            yield piece, many, _from(np.arange(piece.start + 1, piece.stop + 1), many)


def _grouped(group: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of places (first, second) within the runs of equal values."""
    for piece, many, right in _later(group):
        yield np.repeat(np.arange(piece.start, piece.stop), many), right


def _crossed(left: np.ndarray, right: np.ndarray, batch: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Every place of left with every place of right that has the same value; both are sorted."""
    lo, hi = np.searchsorted(right, left, "left"), np.searchsorted(right, left, "right")
    for piece in _pieces(hi - lo, batch):
        many = (hi - lo)[piece]
        if many.any():
            yield np.repeat(np.arange(piece.start, piece.stop), many), _from(lo[piece], many)


class Meetings:
    """The links of the edges ``leads`` of a block, as arrays sorted by (lead, other edge): r (place of the lead), j (the other),
    w (overlap) and mask (which members of the lead are shared).  keep: the links wanted, by lead and other."""

    def __init__(self, block, leads: np.ndarray, keep: Callable[[np.ndarray, np.ndarray], np.ndarray]):
        self.block, self.leads = block, leads
        s = block.s[leads]
        r, place = np.repeat(np.arange(len(leads)), s), _from(np.zeros(len(leads), np.int64), s)
        v = block.v[_from(block.at[leads], s)]
        d = block.of[v + 1] - block.of[v]
        j = block.types[_from(block.of[v], d)].astype(np.int64)
        r, place = np.repeat(r, d), np.repeat(place, d)
        wanted = keep(leads[r], j)
        key = np.sort((r[wanted] << (_LINK + 6)) | (j[wanted] << 6) | place[wanted])
        link = key >> 6
        new = np.ones(len(key), bool)
        new[1:] = link[1:] != link[:-1]
        starts = np.flatnonzero(new)
        kind = next(k for k, most in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.uint64, 64)) if s.max(initial=0) <= most)
        self.of, self.place = np.cumsum(new) - 1, (key & 63).astype(kind)
        self.r, self.j = link[starts] >> _LINK, link[starts] & ((1 << _LINK) - 1)
        self.mask = np.bitwise_or.reduceat(kind(1) << self.place, starts) if len(starts) else np.zeros(0, kind)
        self.kind = np.uint8 if block.n.max(initial=0) < 128 else block.kind  # of sums of two sizes
        self.w, self.n = np.diff(starts, append=len(key)).astype(self.kind), block.n[self.j].astype(self.kind)
        self.ni = block.n[leads].astype(self.kind)[self.r]
        self.nested = self.w == np.minimum(self.n, self.ni)
        self.up = self.nested & (self.n > self.ni)

    def at_vertices(self, among: np.ndarray) -> tuple[np.ndarray, Iterator[tuple[slice, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]]:
        """Links by the vertices of their leads (a link once at each), and the pairs of those that meet at one, in pieces as of
        ``_later``, with how many vertices of the lead they share and whether this is the first: a pair comes once for each."""
        took = among[self.of]
        link = self.of[took]
        key = np.sort((self.r[link] << (_LINK + 6)) | (self.place[took].astype(np.int64) << _LINK) | link)
        group, link = key >> _LINK, key & ((1 << _LINK) - 1)
        one, mask = self.mask.dtype.type(1), self.mask[link]
        below = mask & ((one << (group & 63).astype(self.mask.dtype)) - one)

        def pairs():
            for piece, many, right in _later(group):
                theirs = mask[right]
                yield piece, many, right, np.bitwise_count(np.repeat(mask[piece], many) & theirs), (np.repeat(below[piece], many) & theirs) == 0

        return link, pairs()

    def kinds(self) -> tuple[np.ndarray, np.ndarray]:
        """Kind of each link, by its overlap and both sizes, and a link of each kind."""
        top = int(max(self.n.max(initial=0), self.ni.max(initial=0))) + 1
        key = (self.ni.astype(np.int64) * top + self.n) * top + self.w
        if top**3 > KINDS:
            _, some, kind = np.unique(key, return_index=True, return_inverse=True)
            return kind, some
        some = np.full(top**3, -1)
        some[key] = np.arange(len(key))
        return (np.cumsum(some >= 0) - 1)[key], some[some >= 0]

    @cached_property
    def outside(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(a, b, g, over) of the pairs of links of one lead whose edges share ``over`` > 0 vertices outside of it, g inside."""
        block, mark = self.block, self.block.marks
        own = self.leads
        s = block.s[own]
        mine = np.repeat(np.arange(len(own)) * block.vertices, s) + block.v[_from(block.at[own], s)]
        mark[mine] = True
        s = block.s[self.j]
        spot = np.repeat(self.r * block.vertices, s) + block.v[_from(block.at[self.j], s)]
        key = np.sort(((spot << _LINK) | np.repeat(np.arange(len(self.j)), s))[~mark[spot]])
        mark[mine] = False
        group = key >> _LINK
        same = group[1:] == group[:-1]
        both = np.zeros(len(key), bool)
        both[1:] = same
        both[:-1] |= same
        key = key[both]
        found = [((key[a] & ((1 << _LINK) - 1)) << _LINK) | (key[b] & ((1 << _LINK) - 1)) for a, b in _grouped(key >> _LINK)]
        pairs, over = np.unique(np.concatenate(found), return_counts=True) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        a, b = pairs >> _LINK, pairs & ((1 << _LINK) - 1)
        return a, b, np.bitwise_count(self.mask[a] & self.mask[b]).astype(self.kind), over.astype(self.kind)


def _mended(found: Counter, signed: Callable[..., np.ndarray], a: np.ndarray, b: np.ndarray, g: np.ndarray, over: np.ndarray) -> None:
    """Pairs that were counted as if they shared nothing outside of their lead are counted with what they do."""
    was = Counter()
    _tally(was, signed(a, b, g, np.zeros_like(over)))
    found.subtract(was)
    _tally(found, signed(a, b, g, over))


def _regions(of: Meetings, nests: bool) -> Callable[..., np.ndarray]:
    """Signatures of pairs of links by their seven regions; nests: also those of nest links."""
    w, n, ni, rest = of.w, of.n, of.ni, of.n - of.w

    def signed(a: np.ndarray, b: np.ndarray, g: np.ndarray, over: np.ndarray | None = None) -> np.ndarray:
        wa, wb, na, nb, nia = w[a], w[b], n[a], n[b], ni[a]
        x = g if over is None else g + over
        none = np.zeros(len(g), bool) if over is None else over > 0
        closing = x == np.minimum(na, nb)
        nest = of.nested[a].view(np.uint8) + of.nested[b].view(np.uint8) + closing.view(np.uint8) if nests else np.zeros(len(g), np.uint8)
        left = (rest[a] > 0, rest[b] > 0) if over is None else (rest[a] > over, rest[b] > over)
        sig = _signature(nest, g, (wa > g, wb > g, none), (g + nia > wa + wb, *left))
        sig[x == 0 if nests else (x == 0) | closing] = _OPEN
        return sig

    return signed


def _triads(of: Meetings, among: np.ndarray, nests: bool, found: Counter, core: bool = False) -> None:
    """Pairs of the links ``among`` that meet at a vertex of their lead and, unless ``core``, those that meet outside of it only."""
    signed = _regions(of, nests)
    link, pairs = of.at_vertices(among)
    kind, some = of.kinds()
    most = int(of.w.max(initial=0)) + 1
    if len(some) ** 2 * most <= KINDS:
        got, mine, theirs = np.zeros(len(some) ** 2 * most, np.int64), kind[link] * (len(some) * most), kind[link] * most
        for piece, many, right, g, first in pairs:
            code = np.repeat(mine[piece], many)
            code += theirs[right]
            code += g
            got += np.bincount(code if first.all() else code[first], minlength=len(got))
        at = np.flatnonzero(got)
        _tally(found, signed(some[at // (len(some) * most)], some[at // most % len(some)], (at % most).astype(of.kind)), got[at])
    else:
        for piece, many, right, g, first in pairs:
            sig = signed(np.repeat(link[piece], many), link[right], g.astype(of.kind))
            sig[~first] = _OPEN
            _tally(found, sig)
    _outside(of, among, signed, found, core)


def _outside(of: Meetings, among: np.ndarray, signed: Callable[..., np.ndarray], found: Counter, core: bool) -> None:
    a, b, g, over = of.outside
    here = among[a] & among[b] & (g > 0 if core else True)
    _mended(found, signed, a[here], b[here], g[here], over[here])


def _all(of: Meetings, found: Counter) -> None:
    """Pairs of later links of any kind that meet, by their seven regions."""
    _triads(of, np.ones(len(of.j), bool), True, found)


def _cross(of: Meetings, found: Counter) -> None:
    """Pairs of later cross links that meet, closed by a cross link."""
    _triads(of, ~of.nested, False, found)


def _core_vertex(of: Meetings, found: Counter) -> None:
    """Pairs of later cross links that meet at a vertex of the leading edge, closed by a cross link."""
    _triads(of, ~of.nested, False, found, core=True)


def _baseline(of: Meetings, found: Counter) -> None:
    """Every pair of later links, whether their edges meet or not; those that do by their seven regions."""
    signed = _regions(of, True)
    for piece, many, right in _later(of.r):
        both = np.repeat(of.mask[piece], many) & of.mask[right]
        met = np.flatnonzero(both)
        left = np.repeat(np.arange(piece.start, piece.stop), many)[met]
        _tally(found, signed(left, right[met], np.bitwise_count(both[met]).astype(of.kind)))
    _outside(of, np.ones(len(of.j), bool), signed, found, False)


def _core_grouped(of: Meetings, found: Counter) -> None:
    """Later cross links of one lead and of equal shared sets are a group; a pair of groups is intersected once."""
    signed, links = _regions(of, False), np.flatnonzero(~of.nested)
    links = links[np.lexsort((of.mask[links], of.r[links]))]
    r, mask = of.r[links], of.mask[links]
    new = np.ones(len(links), bool)
    new[1:] = (r[1:] != r[:-1]) | (mask[1:] != mask[:-1])
    starts = np.flatnonzero(new)
    sizes = np.diff(starts, append=len(links))
    for p, q in _grouped(np.cumsum(new)):
        _tally(found, signed(links[p], links[q], np.bitwise_count(mask[p]).astype(of.kind)))
    for p, q in _grouped(r[starts]):
        g = np.bitwise_count(mask[starts[p]] & mask[starts[q]])
        p, q, g = p[g > 0], q[g > 0], g[g > 0]
        for piece in _pieces(sizes[p] * sizes[q], PAIRS):
            one, two = sizes[p[piece]], sizes[q[piece]]
            a, wide = _from(starts[p[piece]], one), np.repeat(two, one)
            b = _from(np.repeat(starts[q[piece]], one), wide)
            _tally(found, signed(links[np.repeat(a, wide)], links[b], np.repeat(g[piece], one * two).astype(of.kind)))
    _outside(of, ~of.nested, signed, found, True)


def _coreless(of: Meetings, found: Counter) -> None:
    """Pairs of later cross links with disjoint shared sets, closed by a cross link outside of the leading edge."""
    two = ~of.nested & (of.n >= 2) & (of.ni >= 2)
    a, b, g, over = of.outside
    here = (g == 0) & two[a] & two[b]
    a, b, x = a[here], b[here], over[here]
    w, n = of.w, of.n
    sig = np.uint8(12) + (of.ni[a] > w[a] + w[b]).view(np.uint8)
    sig += ((n - w)[a] > x).view(np.uint8)
    sig += ((n - w)[b] > x).view(np.uint8)
    sig[x == np.minimum(n[a], n[b])] = _OPEN
    _tally(found, sig)


def _two_nests(of: Meetings, down: Meetings, sig_of: dict[int, int], found: Counter) -> None:
    """Pairs of supersets of an edge, and pairs of its subsets, that cross."""
    ups = np.flatnonzero(of.up)

    def above(a: np.ndarray, b: np.ndarray, g: np.ndarray, over: np.ndarray) -> np.ndarray:
        sig = np.where(over == 0, np.uint8(sig_of[2]), np.uint8(sig_of[3]))
        sig[g + over == np.minimum(of.n[a], of.n[b])] = _OPEN
        return sig

    for p, q in _grouped(of.r[ups]):
        a, b = ups[p], ups[q]
        _tally(found, above(a, b, of.ni[a], np.zeros(len(a), of.kind)))
    if len(ups):
        a, b, g, over = (x[of.up[of.outside[0]] & of.up[of.outside[1]]] for x in of.outside)
        _mended(found, above, a, b, g, over)
    for a, b in _grouped(down.r):
        x, na, nb = np.bitwise_count(down.mask[a] & down.mask[b]).astype(down.kind), down.n[a], down.n[b]
        sig = np.where(na + nb - x == down.ni[a], np.uint8(sig_of[4]), np.uint8(sig_of[5]))
        sig[(x == 0) | (x == np.minimum(na, nb))] = _OPEN
        _tally(found, sig)


def _one_nest(of: Meetings, sig_of: dict[int, int], found: Counter) -> None:
    """Supersets of an edge with the edges that cross both; of: all links of the edges that have supersets."""
    ups, cross = np.flatnonzero(of.up), np.flatnonzero(~of.nested)

    def signed(up: np.ndarray, third: np.ndarray, w: np.ndarray, over: np.ndarray) -> np.ndarray:
        nu, x = of.n[up], w + over
        sig = np.where(over == 0, np.uint8(sig_of[6]), np.where(of.ni[up] + over == nu, np.uint8(sig_of[7]), np.uint8(sig_of[8])))
        sig[x == np.minimum(nu, of.n[third])] = _OPEN
        return sig

    for p, q in _crossed(of.r[ups], of.r[cross], PAIRS):
        up, third = ups[p], cross[q]
        _tally(found, signed(up, third, of.w[third], np.zeros(len(up), of.kind)))
    if len(ups) and len(cross):
        a, b, _, over = of.outside
        for up, third in ((a, b), (b, a)):
            here = of.up[up] & ~of.nested[third]
            _mended(found, signed, up[here], third[here], of.w[third[here]], over[here])


#: The methods that are searched in batches.
BATCHED = ("baseline", "nest_chain", "nest_chain_enumerated", "two_nests", "one_nest", "cross", "core_vertex", "core_grouped", "coreless", "all")


def search(block, names: tuple[str, ...], sig_of: dict[int, int], found: dict[str, Counter]) -> np.ndarray:
    """Counts into ``found`` the triads of the methods ``names`` led by the block's small edges; returns the other leading
    edges, which hold or meet too many.  sig_of: signature of each pattern."""
    degree = np.diff(block.of)[block.v].astype(np.int64)
    total = np.concatenate([[0], np.cumsum(degree)]), np.concatenate([[0], np.cumsum(degree * degree)])
    meetings, pairs = (x[block.at[1:]] - x[block.at[:-1]] for x in total)
    small = block.lead & (block.s <= MEMBERS) & (pairs <= MOST_PAIRS) & (block.vertices <= MARKS)
    leads = np.flatnonzero(small)
    block.marks = np.zeros(MARKS if len(leads) else 0, bool)
    cost = np.maximum(meetings[leads], MEETINGS * block.vertices // MARKS + 1)
    for piece in _pieces(cost, MEETINGS):
        _batch(block, leads[piece], names, sig_of, found)
    del block.marks
    return np.flatnonzero(block.lead & ~small)


def _batch(block, leads: np.ndarray, names: tuple[str, ...], sig_of: dict[int, int], found: dict[str, Counter]) -> None:
    later = Meetings(block, leads, lambda i, j: j > i)
    if {"nest_chain", "nest_chain_enumerated", "two_nests"} & set(names):
        down = Meetings(block, leads, lambda i, j: block.n[j] < block.n[i])
        down = _only(down, down.nested)
        up, low = np.flatnonzero(later.up), np.arange(len(down.j))
    if "nest_chain" in names:
        chains = np.bincount(later.r[up], minlength=len(leads)) * np.bincount(down.r, minlength=len(leads))
        found["nest_chain"][sig_of[1]] += int(chains.sum())
    if "nest_chain_enumerated" in names:
        for p, q in _crossed(later.r[up], down.r, PAIRS):
            found["nest_chain_enumerated"][sig_of[1]] += len(np.column_stack([later.j[up[p]], down.j[low[q]]]))
    if "two_nests" in names:
        _two_nests(later, down, sig_of, found["two_nests"])
    if "one_nest" in names:
        some = np.unique(later.r[later.up])
        some = leads[some[block.n[leads[some]] > 1]]  # an edge of one vertex is crossed by none
        if len(some):
            _one_nest(Meetings(block, some, lambda i, j: j != i), sig_of, found["one_nest"])
    for name, run in (("baseline", _baseline), ("cross", _cross), ("core_vertex", _core_vertex), ("core_grouped", _core_grouped), ("coreless", _coreless), ("all", _all)):
        if name in names:
            run(later, found[name])


def _only(of: Meetings, wanted: np.ndarray) -> Meetings:
    """The wanted links, without their meetings."""
    for x in ("r", "j", "mask", "w", "n", "ni", "nested", "up"):
        setattr(of, x, getattr(of, x)[wanted])
    return of
