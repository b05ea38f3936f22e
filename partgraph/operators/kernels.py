"""Shared-memory routines on one subgraph's rows, in numpy; no Spark here."""

from __future__ import annotations

import zlib

import numpy as np


def triangles_with_inner_edge(src: np.ndarray, dst: np.ndarray, inner: np.ndarray, step: int = 1 << 20):
    """Yield (a, b, c, all three local?) of the triangles with an inner edge, a < b < c, once each.

    Rows are the edges with an end in the subgraph (src < dst); an inner edge has both. The neighbours of the end with
    fewer of them are tested against the other end. A triangle of three inner edges is given by its first two vertices.
    """
    n_edges = len(src)
    if not n_edges or not inner.any():
        return
    ids, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n = len(ids)
    s, d = code[:n_edges].astype(np.int64), code[n_edges:].astype(np.int64)
    u, v = np.concatenate([s, d]), np.concatenate([d, s])
    local_edge = np.concatenate([inner, inner])
    order = np.lexsort((v, u))
    u, v, local_edge = u[order], v[order], local_edge[order]
    first = np.searchsorted(u, np.arange(n + 1))
    deg = np.diff(first)
    keys = u * n + v
    x, y = s[inner], d[inner]
    swap = deg[x] > deg[y]
    lo, hi = np.where(swap, y, x), np.where(swap, x, y)
    ends = np.concatenate([[0], np.cumsum(deg[lo])])
    at = 0
    while at < len(lo):
        stop = max(at + 1, int(np.searchsorted(ends, ends[at] + step, "right")) - 1)
        k = deg[lo[at:stop]]
        edge = np.repeat(np.arange(at, stop), k)
        place = np.arange(int(k.sum())) - np.repeat(np.cumsum(k) - k, k) + np.repeat(first[lo[at:stop]], k)
        z, z_local = v[place], local_edge[place]
        want = hi[edge] * n + z
        pos = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
        hit = (keys[pos] == want) & (~z_local | (z > np.maximum(lo[edge], hi[edge])))
        e, z, whole = edge[hit], z[hit], z_local[hit]
        three = np.sort(np.stack([lo[e], hi[e], z]), axis=0)
        yield ids[three[0]], ids[three[1]], ids[three[2]], whole
        at = stop


def closing_paths(s: np.ndarray, d: np.ndarray, n: int, by: str = "degree", step: int = 1 << 20, table: int = 1 << 25):
    """(``back``, generator of (x, y, z)) of all triangles of the edges (places s < d below ``n``), once each.

    Edges point to the larger place or (degree, place); x, y, z are ranks in that order, ``back`` gives their places. The
    out-neighbours of a run of vertices are marked, a row of marks for each, and the out-lists behind them are read against
    the marks, about ``step`` places at a time: two-step paths are never held together.
    """
    if by == "degree":
        back = np.argsort(np.bincount(s, minlength=n) + np.bincount(d, minlength=n), kind="stable")
        rank = np.empty(n, np.int32)
        rank[back] = np.arange(n, dtype=np.int32)
        s, d = rank[s], rank[d]
        key = np.minimum(s, d).astype(np.int64)
        key *= n
        key += np.maximum(s, d)
    else:
        back = np.arange(n)
        key = s.astype(np.int64)
        key *= n
        key += d
    key.sort()
    if len(key) and (same := key[1:] == key[:-1]).any():
        key = key[np.concatenate([[True], ~same])]

    def run():
        lo = (key // n).astype(np.int32)
        hi = (key - lo * np.int64(n)).astype(np.int32)
        first = np.concatenate([[0], np.cumsum(np.bincount(lo, minlength=n))])
        deg = np.diff(first)
        paths = np.concatenate([[0], np.cumsum(deg[hi])])
        before = paths[first]
        rows = int(max(1, min(table // n, 4096)))
        mark = np.zeros(rows * n, bool)
        at = 0
        while at < n:
            stop = min(n, at + rows, max(at + 1, int(np.searchsorted(before, before[at] + step, "right")) - 1))
            a, b = int(first[at]), int(first[stop])
            if before[stop] > before[at]:
                row = (lo[a:b] - at) * np.int64(n)
                marked = row + hi[a:b]
                mark[marked] = True
                while a < b:
                    end = min(b, max(a + 1, int(np.searchsorted(paths, paths[a] + step, "right")) - 1))
                    mid = hi[a:end]
                    k = deg[mid]
                    start = first[mid] - (paths[a:end] - paths[a])
                    z = hi[np.arange(int(k.sum())) + np.repeat(start, k)]
                    hit = np.flatnonzero(mark[np.repeat(row[len(row) - (b - a) :][: end - a], k) + z])
                    if len(hit):
                        edge = a + np.searchsorted(paths[a : end + 1] - paths[a], hit, "right") - 1 if len(hit) < len(z) // 16 else np.repeat(np.arange(a, end), k)[hit]
                        yield lo[edge], hi[edge], z[hit]
                    a = end
                mark[marked] = False
            at = stop

    return back, run() if len(key) else iter(())


#: Most owners, and bytes of marks, with which triangles are counted by rows of bits.
BIT_OWNERS, BIT_BYTES = 64, 256_000_000


def bits_are_cheaper(s: np.ndarray, d: np.ndarray, n: int, owners: int) -> bool:
    """Whether rows of bits, some 64 places a word, cost less than two-step paths (a path some seven words) and fit."""
    words = n // 64 + 3 * owners
    if not len(s) or owners > BIT_OWNERS or 8 * words * n > BIT_BYTES:
        return False
    degree = np.bincount(s, minlength=n) + np.bincount(d, minlength=n)
    rank = np.empty(n, np.int64)
    rank[np.argsort(degree, kind="stable")] = np.arange(n)
    x, y = rank[s], rank[d]
    out = np.bincount(np.minimum(x, y), minlength=n)
    return len(s) * words + 20_000 * n < 7 * float(out[np.maximum(x, y)].sum())


def closing_counts(s: np.ndarray, d: np.ndarray, n: int, own: np.ndarray, owners: int, colour: np.ndarray, paint: list[int]) -> np.ndarray:
    """Triangles a < b < c by the owners of a, b and c, of those that have one vertex of each colour of ``paint`` (three,
    repeats allowed).

    A place has a row of bits for its larger neighbours of each colour, in order of their owners, from a whole word on for
    each. For an edge (a, b) the rows of the colour that is left are met, and bits counted by the owners of b and c.
    """
    total = np.zeros((owners, owners, owners), np.int64)
    if not len(s):
        return total
    lo, hi = np.minimum(s, d).astype(np.int64), np.maximum(s, d).astype(np.int64)
    palette = sorted(set(paint))
    shade = np.searchsorted(palette, colour)
    key = ((lo * len(palette) + shade[hi]) * owners + own[hi]) * n + hi
    del lo, hi
    key.sort()
    if len(key) and (same := key[1:] == key[:-1]).any():
        key = key[np.concatenate([[True], ~same])]
    hi = (key % n).astype(np.int32)
    key //= n
    first = np.searchsorted(key // (owners * len(palette)), np.arange(n + 1))
    rows, segments = [], []
    for c in range(len(palette)):
        of_owner = np.bincount(own[shade == c], minlength=owners)
        wide = -(-of_owner // 64)
        begin = np.cumsum(wide) - wide
        place = np.zeros(n, np.int64)
        mine = np.flatnonzero(shade == c)
        mine = mine[np.argsort(own[mine], kind="stable")]
        nth = np.arange(len(mine)) - np.repeat(np.cumsum(of_owner) - of_owner, of_owner)
        place[mine] = begin[own[mine]] * 64 + nth
        width = int(wide.sum())
        bits = np.zeros((n, width), np.uint64)
        step = max(1, (1 << 25) // max(1, 64 * width))
        for at in range(0, n, step):
            stop = min(n, at + step)
            seen = slice(int(first[at]), int(first[stop]))
            far = hi[seen]
            near = np.repeat(np.arange(stop - at), np.diff(first[at : stop + 1]))
            some = shade[far] == c
            marks = np.zeros((stop - at, width * 64), bool)
            marks[near[some], place[far[some]]] = True
            bits[at:stop] = np.packbits(marks, axis=1, bitorder="little").view(np.uint64)
        rows.append(bits)
        held = np.flatnonzero(wide)
        segments.append((held, begin[held]))
    left = {}
    for x in range(len(palette)):
        for y in range(len(palette)):
            rest = list(paint)
            try:
                rest.remove(palette[x])
                rest.remove(palette[y])
            except ValueError:
                continue
            left[x, y] = palette.index(rest[0])
    # runs of one a and colour of b, cut by the owner of b
    fresh = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    owner_of = key[fresh] % owners
    run_of = key[fresh] // owners
    run = np.flatnonzero(np.concatenate([[True], run_of[1:] != run_of[:-1]]))
    for i, j in zip(run.tolist(), [*run[1:].tolist(), len(fresh)], strict=True):
        a, y = divmod(int(run_of[i]), len(palette))
        c = left.get((int(shade[a]), y))
        if c is None or not rows[c].shape[1]:
            continue
        start = int(fresh[i])
        stop = int(fresh[j]) if j < len(fresh) else len(hi)
        met = rows[c][hi[start:stop]]
        met &= rows[c][a]
        by_b = np.add.reduceat(np.bitwise_count(met), fresh[i:j] - start, axis=0, dtype=np.uint32)
        held, begin = segments[c]
        by_c = np.add.reduceat(by_b, begin, axis=1, dtype=np.int64)
        total[own[a], owner_of[i:j, None], held] += by_c
    return total


def _planes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T).tobytes()


def _from_planes(raw: memoryview, n: int, dtype) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * size).reshape(size, n).T).view(dtype).reshape(n)


def packed_edges(src: np.ndarray, dst: np.ndarray) -> bytes:
    """The edges in a few bytes each: steps between sorted ids, counts of each first end, steps between second ends."""
    ids, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n, m = len(ids), len(src)
    key = code[:m].astype(np.int64) * n + code[m:]
    key.sort()
    s = key // n
    d = (key - s * n).astype(np.int32)
    step = d.copy()
    step[1:] -= np.where(s[1:] == s[:-1], d[:-1], 0).astype(np.int32)
    head = np.array([n, m], np.int64).tobytes()
    return zlib.compress(head + _planes(np.diff(ids, prepend=np.int64(0))) + _planes(np.bincount(s, minlength=n).astype(np.uint32)) + _planes(step), 1)


def unpacked_edges(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, s, d) of packed edges: sorted ids, and the places of both ends among them."""
    raw = memoryview(zlib.decompress(blob))
    n, m = (int(x) for x in np.frombuffer(raw[:16], np.int64))
    ids = np.cumsum(_from_planes(raw[16:], n, np.int64))
    count = _from_planes(raw[16 + 8 * n :], n, np.uint32).astype(np.int64)
    step = _from_planes(raw[16 + 12 * n :], m, np.int32).astype(np.int64)
    total = np.cumsum(step)
    some = count > 0
    first = (np.cumsum(count) - count)[some]
    d = total - np.repeat(total[first] - step[first], count[some])
    return ids, np.repeat(np.arange(n, dtype=np.int32), count), d.astype(np.int32)


def packed_longs(*columns: np.ndarray) -> bytes:
    """Columns of one length, of 64-bit whole numbers."""
    return zlib.compress(np.array([len(columns[0])], np.int64).tobytes() + b"".join(map(_planes, columns)), 1)


def unpacked_longs(blob: bytes, columns: int) -> list[np.ndarray]:
    raw = memoryview(zlib.decompress(blob))
    n = int(np.frombuffer(raw[:8], np.int64)[0])
    return [_from_planes(raw[8 + 8 * n * c :], n, np.int64) for c in range(columns)]


def pairs_within(group: np.ndarray, member: np.ndarray, step: int = 1 << 22):
    """Yield (src, dst, n), src < dst and sorted, of the members that share a group; n counts pairs of their rows.

    Pairs are formed and summed about ``step`` at a time: one that meets in several groups may be given several times.
    """
    ids, code = np.unique(member, return_inverse=True)
    order = np.lexsort((code, group))
    group, code = group[order], code[order].astype(np.int64)
    new = np.flatnonzero(np.concatenate([[True], (group[1:] != group[:-1]) | (code[1:] != code[:-1])])) if len(group) else np.zeros(0, np.int64)
    rows = np.diff(new, append=len(group))
    group, code = group[new], code[new]
    k = np.searchsorted(group, group, "right") - 1 - np.arange(len(group))
    ends = np.cumsum(k)
    at = 0
    while at < len(group):
        done = int(ends[at - 1]) if at else 0
        stop = max(at + 1, int(np.searchsorted(ends, done + step, "right")))
        part = k[at:stop]
        left = np.repeat(np.arange(at, stop), part)
        right = left + 1 + np.arange(len(left)) - np.repeat(np.cumsum(part) - part, part)
        if len(left):
            key, n = summed(code[left] * len(ids) + code[right], rows[left] * rows[right])
            yield ids[key // len(ids)], ids[key % len(ids)], n
        at = stop


def summed(key: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys, sorted, and the sum of ``n`` of each."""
    order = np.argsort(key, kind="stable")
    key = key[order]
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    return key[first], np.add.reduceat(n[order], first) if len(first) else np.zeros(0, np.int64)


def colour_of(ids: np.ndarray, colours: int) -> np.ndarray:
    """A hash of each id below ``colours``."""
    x = ids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((x ^ (x >> np.uint64(29))) % np.uint64(colours)).astype(np.int64)


def forest_within(src: np.ndarray, dst: np.ndarray, weight: np.ndarray, inner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(chosen inner edges, vertices, their roots) of merging along least edges while these are inner.

    Rows are all edges with an end in the subgraph, the remote ones included: a tree whose least edge is remote waits.
    Ties are broken by (weight, src, dst); a root is the least vertex of its tree.
    """
    ids, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n_edges = len(src)
    a, b = code[:n_edges], code[n_edges:]
    rank = np.empty(n_edges, np.int64)
    rank[np.lexsort((dst, src, weight))] = np.arange(n_edges)
    by_rank = np.argsort(rank)
    root = np.arange(len(ids))
    here = np.zeros(len(ids), bool)
    here[a[inner]] = here[b[inner]] = True
    chosen = np.zeros(n_edges, bool)
    while True:
        ra, rb = root[a], root[b]
        out = ra != rb
        least = np.full(len(ids), n_edges, np.int64)
        np.minimum.at(least, ra[out], rank[out])
        np.minimum.at(least, rb[out], rank[out])
        asks = np.flatnonzero((least < n_edges) & here[np.arange(len(ids))])
        asks = asks[inner[by_rank[least[asks]]]]
        if not len(asks):
            break
        e = by_rank[least[asks]]
        chosen[e] = True
        # merge the two trees of every chosen edge; each becomes the least vertex among those joined
        low, high = root[a[e]], root[b[e]]
        while True:
            m = np.minimum(root[low], root[high])
            before = root.copy()
            np.minimum.at(root, low, m)
            np.minimum.at(root, high, m)
            root = root[root]
            if (before == root).all() and (root[low] == root[high]).all():
                break
        while (root != root[root]).any():
            root = root[root]
    return chosen, ids[here], ids[root[here]]


def hops_within(u: np.ndarray, v: np.ndarray, vid: np.ndarray, dist: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least (dist, rank) of each row of ``vid`` by any path of the arcs u -> v (both ends among ``vid``); unreached: -1."""
    far = np.iinfo(np.int64).max
    value = np.where(dist >= 0, dist.astype(np.int64) << 32 | rank.astype(np.int64), far)
    order = np.argsort(vid)
    a, b = order[np.searchsorted(vid, u, sorter=order)], order[np.searchsorted(vid, v, sorter=order)]
    while len(a):
        new = value.copy()
        known = value[a] < far
        np.minimum.at(new, b[known], value[a[known]] + (1 << 32))
        if (new == value).all():
            break
        value = new
    reached = value < far
    return np.where(reached, value >> 32, -1), np.where(reached, value & 0xFFFFFFFF, -1)
