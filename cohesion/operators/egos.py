"""Communities of dense graphs by neighbourhoods: no clique is listed but one for each vertex of a community.

The k-cliques at a vertex v are v and the (k-1)-cliques among its neighbours, and two of them are adjacent if those are.
So the communities at k are the communities at k-1 within each neighbourhood, joined where two of them hold the same
k-cliques; at k = 2 they are components. Vertex sets are bitmaps, so that a search of a dense neighbourhood takes a few
steps. The work grows with the (k-2)-cliques, not with maximal cliques, of which dense graphs have too many to list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Vertices up to which bitmaps are over the whole graph (of n * n / 8 bytes); more have bitmaps over each neighbourhood.
WHOLE = 50_000
#: Rows of a graph's bitmaps that are filled at once.
ROWS = 1_024


def _bits(mask: int) -> Iterator[int]:
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def _components(near: list[int], mask: int) -> list[tuple[int, tuple[int, ...]]]:
    """(vertices, least link) of each component with a link of the graph on mask."""
    out = []
    while mask:
        low = mask & -mask
        mask ^= low
        x = low.bit_length() - 1
        edge = near[x] & mask
        if edge:
            own = low | edge
            mask ^= edge
            least = (x, (edge & -edge).bit_length() - 1)
            while edge and mask:
                low = edge & -edge
                edge ^= low
                new = near[low.bit_length() - 1] & mask
                mask ^= new
                own |= new
                edge |= new
            out.append((own, least))
    return out


def _triangles(near: list[int], mask: int) -> tuple[list[tuple[int, ...]], list[tuple[int, tuple[int, ...], int]]]:
    """(least triangle of each community, (vertex, rest of its least triangle there, community)) on mask at k = 3."""
    parts: dict[int, list[tuple[int, tuple[int, ...]]]] = {}
    single = several = 0
    for v in _bits(mask):
        found = _components(near, near[v] & mask)
        if found:
            parts[v] = found
            if len(found) == 1:
                single |= 1 << v
            else:
                several |= 1 << v
    seen: dict[tuple[int, int], int] = {}
    least: list[tuple[int, ...]] = []
    for v, found in parts.items():
        for i, (_, rest) in enumerate(found):
            if (v, i) in seen:
                continue
            label = len(least)
            least.append((v, *rest))
            seen[v, i] = label
            single &= ~(1 << v)
            todo = [(v, i)]
            while todo:
                w, j = todo.pop()
                reach = parts[w][j][0]
                new = reach & single
                if new:
                    single ^= new
                    for x in _bits(new):
                        seen[x, 0] = label
                        todo.append((x, 0))
                for x in _bits(reach & several):
                    at = next(n for n, (own, _) in enumerate(parts[x]) if own >> w & 1)
                    if (x, at) not in seen:
                        seen[x, at] = label
                        todo.append((x, at))
                if not single and not several:
                    break
    for (v, i), label in seen.items():
        least[label] = min(least[label], tuple(sorted((v, *parts[v][i][1]))))
    return least, [(v, parts[v][i][1], label) for (v, i), label in seen.items()]


def _solve(near: list[int], mask: int, k: int) -> tuple[list[tuple[int, ...]], list[tuple[int, tuple[int, ...], int]]]:
    """As _triangles, at any k from 2 on; at k = 2 the rest is empty."""
    if k == 2:
        found = _components(near, mask)
        return [least for _, least in found], [(v, (), n) for n, (own, _) in enumerate(found) for v in _bits(own)]
    if k == 3:
        return _triangles(near, mask)
    return _joined(((v, None, *_solve(near, near[v] & mask, k - 1)) for v in _bits(mask)))


def _joined(each) -> tuple[list[tuple[int, ...]], list[tuple[int, tuple[int, ...], int]]]:
    """Communities of (vertex, names, communities of its neighbourhood) in the order of vertices; names None: as they are."""
    parent: list[int] = []
    nodes: list[tuple[int, tuple[int, ...]]] = []
    waits: dict[tuple, int] = {}

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for v, names, least, index in each:
        base = len(parent)
        named = (lambda t: t) if names is None else (lambda t: tuple(names[x] for x in t))  # noqa: B023
        nodes += [(v, named(t)) for t in least]
        parent += range(base, base + len(least))
        for w, rest, label in index:
            w, rest = (w if names is None else names[w]), named(rest)
            # The same cliques are in the neighbourhood of either end of the link v - w.
            if v < w:
                waits[v, w, rest] = base + label
            else:
                a, b = find(waits.pop((w, v, rest))), find(base + label)
                if a != b:
                    parent[max(a, b)] = min(a, b)
    number: dict[int, int] = {}
    out: list[tuple[int, ...]] = []
    index = []
    for n, (v, rest) in enumerate(nodes):
        r = find(n)
        clique = tuple(sorted((v, *rest)))
        if r not in number:
            number[r] = len(out)
            out.append(clique)
        out[number[r]] = min(out[number[r]], clique)
        index.append((v, rest, number[r]))
    return out, index


def ego_covers(src: np.ndarray, dst: np.ndarray, k: int, whole: int = WHOLE) -> list[tuple[tuple[int, ...], tuple[int, ...]]]:
    """(least k-clique, k-clique) rows, ids ascending: for each community one k-clique or more at each of its vertices."""
    keep = src != dst
    src, dst = src[keep], dst[keep]
    ids = np.union1d(src, dst)
    n = len(ids)
    a = np.concatenate([np.searchsorted(ids, src), np.searchsorted(ids, dst)]).astype(np.int32)
    b = np.concatenate([a[len(src) :], a[: len(src)]])
    order = np.argsort(a, kind="stable")
    b = b[order]
    bounds = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=n))])
    del a, order
    if n <= whole:
        near = []
        for at in range(0, n, ROWS):
            end = min(n, at + ROWS)
            bits = np.zeros((end - at, n), np.uint8)
            bits[np.repeat(np.arange(end - at), np.diff(bounds[at : end + 1])), b[bounds[at] : bounds[end]]] = 1
            near += [int.from_bytes(row.tobytes(), "little") for row in np.packbits(bits, axis=1, bitorder="little")]
        least, index = _solve(near, (1 << n) - 1, k)
    else:

        def each():
            for v in range(n):
                names = np.unique(b[bounds[v] : bounds[v + 1]])
                # The neighbours of each neighbour, cut to those of v.
                sizes = bounds[names + 1] - bounds[names]
                first = np.repeat(bounds[names] - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes)
                theirs = b[first + np.arange(len(first))]
                place = np.searchsorted(names, theirs).clip(0, len(names) - 1)
                inside = names[place] == theirs
                bits = np.zeros((len(names), len(names)), np.uint8)
                bits[np.repeat(np.arange(len(names)), sizes)[inside], place[inside]] = 1
                near = [int.from_bytes(row.tobytes(), "little") for row in np.packbits(bits, axis=1, bitorder="little")]
                yield v, names.tolist(), *_solve(near, (1 << len(names)) - 1, k - 1)

        least, index = _joined(each())
    named = ids.tolist()
    own = [tuple(named[x] for x in t) for t in least]
    return [(own[label], tuple(sorted(named[x] for x in (v, *rest)))) for v, rest, label in index]
