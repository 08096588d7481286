"""Reverse-reachable sets within a piece of the graph that one task holds.

The draw of an edge in a set is the hash that `hash31(h, set, seed)` gives, computed on whole arrays. A small set is
found by expanding its vertices. A set whose vertices have many arcs is found from one pass over the edges of the
piece: each edge is then drawn once, in place of once from each of its ends.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from spreadmax.functions.hashing import INT_MAX
from spreadmax.operators.components import hooked

#: A set whose vertices have more arcs than this share of what a pass costs is drawn by a pass over all edges of the piece. A pass costs its
#: edges and, for its calls, so many more.
PASS_SHARE, PASS_EDGES = 1 / 64, 1 << 18
#: Edges that are drawn at once for a set; they and two buffers stay in a core's cache.
STRIP = 65536
#: Arcs that are expanded at once, and (set, vertex) cells of a batch of sets.
ARCS, CELLS = 1 << 20, 1 << 22
#: Murmur3's numbers, as NumPy scalars since those need no conversion at each call.
_U = {x: np.uint32(x) for x in (5, 8, 13, 16, 19, INT_MAX, 0xE6546B64, 0x85EBCA6B, 0xC2B2AE35)}


def _mixed(k: np.ndarray) -> np.ndarray:
    k = k.astype(np.uint32) * np.uint32(0xCC9E2D51)
    return ((k << np.uint32(15)) | (k >> np.uint32(17))) * np.uint32(0x1B873593)


def mixed_halves(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both 32-bit halves of 64-bit numbers, as Murmur3 mixes them before they meet the state."""
    x = np.asarray(x, np.int64).view(np.uint64)
    return _mixed(x & np.uint64(0xFFFFFFFF)), _mixed(x >> np.uint64(32))


def hash_step(s: np.ndarray, low, high, t: np.ndarray, last: bool = False, out: np.ndarray | None = None) -> None:
    """Murmur3 of one more 64-bit number: the states `s` (uint32) become the next ones, in `out` or in place; `t` is a
    buffer like `s`. `last` leaves out the last step, which changes the low 16 bits only."""
    given, s = s, s if out is None else out
    for half in (low, high):
        if given is not s or np.ndim(half) or half:
            np.bitwise_xor(given, half, out=s)
        given = s
        np.right_shift(s, _U[19], out=t)
        np.left_shift(s, _U[13], out=s)
        np.bitwise_or(s, t, out=s)
        np.multiply(s, _U[5], out=s)
        np.add(s, _U[0xE6546B64], out=s)
    np.bitwise_xor(s, _U[8], out=s)
    for shift, factor in ((16, 0x85EBCA6B), (13, 0xC2B2AE35)):
        np.right_shift(s, _U[shift], out=t)
        np.bitwise_xor(s, t, out=s)
        np.multiply(s, _U[factor], out=s)
    if not last:
        np.right_shift(s, _U[16], out=t)
        np.bitwise_xor(s, t, out=s)


class Piece:
    """Edges between the vertices 0 .. n-1: `state` is the hash of an edge's own hash, `thr` its threshold."""

    def __init__(self, n: int, a: np.ndarray, b: np.ndarray, state: np.ndarray, thr: np.ndarray, seed: int):
        self.n, self.a, self.b, self.state, self.thr = n, a, b, state.view(np.uint32), thr
        order = np.argsort(np.concatenate((a, b)), kind="stable")
        self.ends = np.concatenate((b, a))[order]
        self.edge = np.concatenate((np.arange(len(a)), np.arange(len(a))))[order]
        self.begin = np.concatenate(([0], np.cumsum(np.bincount(np.concatenate((a, b)), minlength=n))))
        self.most = np.where(thr < 0, 0, thr | 0xFFFF).astype(np.uint32)  # what the high bits of a kept draw do not exceed
        self.same = self.most[0] if len(thr) and (self.most == self.most[0]).all() else None
        self.seed = tuple(k[0] for k in mixed_halves(np.array([seed])))

    def _kept(self, state: np.ndarray, low, high, at, s: np.ndarray, t: np.ndarray) -> np.ndarray:
        """Which of the edges `at` with these states are kept in the sets of `low` and `high`; `s` and `t` are buffers."""
        hash_step(state, low, high, t, out=s)
        hash_step(s, *self.seed, t, last=True)
        np.bitwise_and(s, _U[INT_MAX], out=t)
        hit = np.flatnonzero(t <= (self.most[at] if self.same is None else self.same))
        x = s[hit]
        thr = self.thr[at[hit] if isinstance(at, np.ndarray) else hit + at.start]
        return hit[((x ^ (x >> 16)) & INT_MAX).astype(np.int64) <= thr]

    def expanded(self, sets: np.ndarray, roots: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(set, vertex) of small sets, and which sets are left to a pass over the edges."""
        low, high = mixed_halves(sets)
        many = max(64, int(PASS_SHARE * (len(self.a) + PASS_EDGES)))
        seen = np.zeros(len(sets) * self.n, bool)
        tested, left = np.zeros(len(sets), np.int64), np.zeros(len(sets), bool)
        front = np.arange(len(sets)) * self.n + roots
        found = [front]
        seen[front] = True
        while len(front):
            j, u = front // self.n, front % self.n
            size = self.begin[u + 1] - self.begin[u]
            tested += np.bincount(j, size, len(sets)).astype(np.int64)
            left |= tested > many
            go = ~left[j] & (size > 0)
            j, u, size = j[go], u[go], size[go]
            cuts = np.searchsorted(np.cumsum(size), np.arange(ARCS, size.sum(), ARCS)) if len(size) else []
            new = []
            for jj, uu, ss in zip(*(np.split(x, np.unique(cuts)) if len(cuts) else [x] for x in (j, u, size)), strict=True):
                at = np.arange(ss.sum()) + np.repeat(self.begin[uu] - np.cumsum(ss) + ss, ss)
                jj = np.repeat(jj, ss)
                e = self.edge[at]
                state = self.state[e]
                hit = self._kept(state, low[jj], high[jj], e, np.empty_like(state), np.empty_like(state))
                to = jj[hit] * self.n + self.ends[at[hit]]
                new.append(to[~seen[to]])
            front = np.unique(np.concatenate(new)) if new else np.zeros(0, np.int64)
            front = front[~seen[front]]
            seen[front] = True
            found.append(front)
        every = np.concatenate(found)
        every = every[~left[every // self.n]]
        return every // self.n, every % self.n, left

    def passed(self, sets: np.ndarray, roots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(set, vertex) of sets from one pass over all edges each."""
        low, high = mixed_halves(sets)
        none = np.zeros(0, np.int64)
        by, edges = [none], [none]
        s, t = np.empty(STRIP, np.uint32), np.empty(STRIP, np.uint32)
        for at in range(0, len(self.a), STRIP):
            strip = slice(at, min(at + STRIP, len(self.a)))
            state, size = self.state[strip], strip.stop - at
            for j in range(len(sets)):
                hit = self._kept(state, low[j], high[j], strip, s[:size], t[:size])
                if len(hit):
                    by.append(np.full(len(hit), j))
                    edges.append(hit + at)
        base, e = np.concatenate(by) * self.n, np.concatenate(edges)
        root = hooked(base + self.a[e], base + self.b[e], len(sets) * self.n).reshape(len(sets), self.n)
        return np.nonzero(root == root[np.arange(len(sets)), roots][:, None])

    def members(self, sets: np.ndarray, roots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number of the set, vertex) of all members of the sets, which begin at `roots`."""
        batch, out = max(1, CELLS // max(1, self.n)), []
        for at in range(0, len(sets), batch):
            own, begin = sets[at : at + batch], roots[at : at + batch]
            j, v, left = self.expanded(own, begin)
            out.append((own[j], v))
            if left.any():
                own, begin = own[left], begin[left]
                j, v = self.passed(own, begin)
                out.append((own[j], v))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 2


PACKED = "bucket int, label long, chunk int, ids binary, a binary, b binary, state binary, thr binary"


def packed(edges: pa.Table) -> pa.Table:
    """A piece (bucket, label, src, dst, state, thr) as a few rows of arrays: its vertices in order, and the edges by their numbers.

    Every part of the sets of a piece reads the piece anew; a row of arrays is moved and decoded at once.
    """
    src, dst, state, thr = (edges.column(c).to_numpy() for c in ("src", "dst", "state", "thr"))
    ids, flat = np.unique(np.concatenate((src, dst)), return_inverse=True)
    a, b = np.split(flat.astype(np.int32), 2)
    chunks = -(-max(len(ids), len(a)) // STRIP)
    cut = lambda x: pa.array([x[c * STRIP : (c + 1) * STRIP].tobytes() for c in range(chunks)], pa.binary())
    key = {c: edges.column(c).slice(0, 1).to_pylist() * chunks for c in ("bucket", "label")}
    fields = [("bucket", pa.int32()), ("label", pa.int64()), ("chunk", pa.int32())]
    columns = [*(pa.array(key[c], kind) for c, kind in fields[:2]), pa.array(range(chunks), pa.int32())]
    return pa.table([*columns, *map(cut, (ids, a, b, state, thr))], [*(c for c, _ in fields), "ids", "a", "b", "state", "thr"])


def _unpacked(rows: pa.Table) -> list[np.ndarray]:
    rows = rows.sort_by("chunk")
    kinds = (("ids", np.int64), ("a", np.int32), ("b", np.int32), ("state", np.int32), ("thr", np.int32))
    return [np.frombuffer(b"".join(rows.column(c).to_pylist()), kind) for c, kind in kinds]


def solver(seed: int):
    """The kernel of `rr_sets`: roots (rr_id, id) and edges of a piece, as rows of `packed` or as (src, dst, state, thr) -> (rr_id, id)."""

    def solve(roots: pa.Table, edges: pa.Table) -> pa.Table:
        sets, starts = (roots.column(c).to_numpy() for c in ("rr_id", "id"))
        if "chunk" in edges.column_names:
            own, a, b, state, thr = _unpacked(edges)
            ids = np.union1d(own, starts)  # a root may have no edge
            if len(ids) > len(own):
                at = np.searchsorted(ids, own)
                a, b = at[a], at[b]
            begin = np.searchsorted(ids, starts)
        else:
            src, dst, state, thr = (edges.column(c).to_numpy() for c in ("src", "dst", "state", "thr"))
            ids, flat = np.unique(np.concatenate((src, dst, starts)), return_inverse=True)
            a, b, begin = np.split(flat, [len(src), 2 * len(src)])
        rr, v = Piece(len(ids), a, b, state, thr, seed).members(sets, begin)
        return pa.table({"rr_id": rr, "id": ids[v]})

    return solve
