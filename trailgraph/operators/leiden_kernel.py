"""Leiden communities of one small graph, in memory (published algorithm: move, refine, aggregate).

Directed weighted modularity; the gain of i joining C is
    w(i,C) + w(C,i) - resolution * (out_i * in_C + in_i * out_C) / m
with m given by the caller (A25). Results depend on ids, weights and seed only: nodes are visited in
an order drawn from the seed, ties go to the smallest label, and the random merge of the published
method is a best-gain merge.
"""

from __future__ import annotations

import random
from collections import deque

_EPS = 1e-12
RESTARTS = 3


class _Level:
    """A graph of aggregated nodes: symmetric link weights, strengths and numbers of original nodes."""

    def __init__(self, links, out, inn, size):
        self.links, self.out, self.inn, self.size, self.n = links, out, inn, size, len(size)


def _move(g: _Level, comm: list[int], order: list[int], rule: tuple, cap) -> bool:
    """``rule``: (whether CPM, resolution, m). Sums over communities are lists and terms are written out, as this loop takes most of the time."""
    cpm, resolution, m = rule
    links, free, moved = g.links, max(comm, default=0) + 1, False
    outs, inns, sizes = [0.0] * free, [0.0] * free, [0] * free
    for i, c in enumerate(comm):
        outs[c] += g.out[i]
        inns[c] += g.inn[i]
        sizes[c] += g.size[i]
    queue, waiting = deque(order), [True] * g.n
    while queue:
        i = queue.popleft()
        waiting[i] = False
        old, o, n, s, to = comm[i], g.out[i], g.inn[i], g.size[i], {}
        for j, w in links[i].items():
            c = comm[j]
            to[c] = to[c] + w if c in to else w
        outs[old] -= o
        inns[old] -= n
        sizes[old] -= s
        best, top = old, to.get(old, 0.0) - (resolution * s * sizes[old] if cpm else resolution * (o * inns[old] + n * outs[old]) / m)
        for c in sorted(to):
            if c != old and (cap is None or sizes[c] + s <= cap):
                x = to[c] - (resolution * s * sizes[c] if cpm else resolution * (o * inns[c] + n * outs[c]) / m)
                if x > top + _EPS:
                    best, top = c, x
        if top < -_EPS:  # better alone
            best, free = free, free + 1
            outs.append(0.0)
            inns.append(0.0)
            sizes.append(0)
        outs[best] += o
        inns[best] += n
        sizes[best] += s
        if best != old:
            comm[i], moved = best, True
            for j in links[i]:
                if comm[j] != best and not waiting[j]:
                    waiting[j] = True
                    queue.append(j)
    return moved


def _refine(g: _Level, comm: list[int], order: list[int], rule: tuple) -> list[int]:
    """Sub-communities, grown from single nodes inside each community; only well-connected ones merge."""
    cpm, resolution, m = rule
    k = max(comm, default=0) + 1
    all_out, all_in, all_size = [0.0] * k, [0.0] * k, [0] * k
    for i, c in enumerate(comm):
        all_out[c] += g.out[i]
        all_in[c] += g.inn[i]
        all_size[c] += g.size[i]
    part, alone, outs, inns, sizes = list(range(g.n)), [True] * g.n, list(g.out), list(g.inn), list(g.size)
    ties = [sum([w for j, w in g.links[i].items() if comm[j] == comm[i]]) for i in range(g.n)]  # of each part to the rest of its community
    for i in order:
        c, o, n, s = comm[i], g.out[i], g.inn[i], g.size[i]
        if not alone[i] or ties[i] + _EPS < (resolution * s * (all_size[c] - s) if cpm else resolution * (o * (all_in[c] - n) + n * (all_out[c] - o)) / m):
            continue
        to = {}
        for j, w in g.links[i].items():
            if comm[j] == c:
                p = part[j]
                to[p] = to[p] + w if p in to else w
        best, top = i, 0.0
        for p in sorted(to):
            if p == i:
                continue
            so, si, sz = outs[p], inns[p], sizes[p]
            need = resolution * sz * (all_size[c] - sz) if cpm else resolution * (so * (all_in[c] - si) + si * (all_out[c] - so)) / m
            x = to[p] - (resolution * s * sz if cpm else resolution * (o * si + n * so) / m)
            if ties[p] + _EPS >= need and x > top + _EPS:
                best, top = p, x
        if best != i:
            outs[best] += o
            inns[best] += n
            sizes[best] += s
            ties[best] = ties[best] + ties[i] - 2 * to[best]
            part[i], alone[i], alone[best] = best, False, False
    return part


def _aggregate(g: _Level, part: list[int]) -> tuple[_Level, list[int]]:
    index: dict[int, int] = {}
    new = [index.setdefault(p, len(index)) for p in part]
    n = len(index)
    links: list[dict[int, float]] = [{} for _ in range(n)]
    out, inn, size = [0.0] * n, [0.0] * n, [0] * n
    for i in range(g.n):
        a = new[i]
        out[a] += g.out[i]
        inn[a] += g.inn[i]
        size[a] += g.size[i]
        for j, w in g.links[i].items():
            if new[j] != a:
                links[a][new[j]] = links[a].get(new[j], 0.0) + w
    return _Level(links, out, inn, size), new


def _split_loose(n: int, links, comm: list[int]) -> list[int]:
    """Communities cut into their connected parts."""
    label = [-1] * n
    for i in range(n):
        if label[i] < 0:
            label[i], todo = i, [i]
            while todo:
                x = todo.pop()
                for j in links[x]:
                    if label[j] < 0 and comm[j] == comm[i]:
                        label[j] = i
                        todo.append(j)
    return label


def run(src: list, dst: list, w: list, m: float | None = None, resolution: float = 1.0, max_comm_size: int | None = None, seed: int = 42, quality: str = "modularity", directed: bool = True, max_iterations: int = 50, size: dict | None = None) -> dict:
    """Edges of any hashable, sortable ids -> {id: least id of its community}.

    Every graph, whatever its size, is solved from ``RESTARTS`` visiting orders and the best labelling stays. ``size``: how many original nodes each id stands for (1).
    """
    kw = dict(m=m, resolution=resolution, max_comm_size=max_comm_size, quality=quality, directed=directed, max_iterations=max_iterations, size=size)
    if len(src) == 1 or quality != "modularity":
        return _solve(src, dst, w, seed=seed, **kw)
    return max((one_start(src, dst, w, seed + k, **kw) for k in range(RESTARTS)), key=lambda x: x[0])[1]


def one_start(src: list, dst: list, w: list, seed: int, **kw) -> tuple[float, dict]:
    """(modularity, labelling) from one visiting order."""
    lab, m, resolution = _solve(src, dst, w, seed=seed, **kw), kw["m"], kw["resolution"]
    if kw["directed"]:
        return round(modularity(src, dst, w, lab, m, resolution), 12), lab
    return round(modularity([*src, *dst], [*dst, *src], [*w, *w], lab, None if m is None else 2 * m, resolution), 12), lab


def _solve(src: list, dst: list, w: list, m: float | None, resolution: float, max_comm_size: int | None, seed: int, quality: str, directed: bool, max_iterations: int = 50, size: dict | None = None) -> dict:
    names = sorted({*src, *dst})
    at = {x: i for i, x in enumerate(names)}
    n = len(names)
    links: list[dict[int, float]] = [{} for _ in range(n)]
    out, inn = [0.0] * n, [0.0] * n
    for s, d, x in zip(src, dst, w):
        i, j, x = at[s], at[d], float(x)
        out[i] += x
        inn[j] += x
        if not directed:
            out[j] += x
            inn[i] += x
        if i != j:
            k = x if directed else 2 * x
            links[i][j] = links[i].get(j, 0.0) + k
            links[j][i] = links[j].get(i, 0.0) + k
    m = (sum(map(float, w)) if m is None else float(m)) * (1 if directed else 2)
    if m <= 0 or not n:
        return {x: x for x in names}
    rule = (quality == "cpm", resolution, m)
    rng = random.Random(f"{seed}:{names[0]}")
    g, comm, home = _Level(links, out, inn, [1] * n if size is None else [int(size[x]) for x in names]), list(range(n)), list(range(n))
    for _ in range(max_iterations):
        order = list(range(g.n))
        rng.shuffle(order)
        moved = _move(g, comm, order, rule, max_comm_size)
        if not moved and len(set(comm)) == g.n:
            break
        rng.shuffle(order)
        part = _refine(g, comm, order, rule)
        after, new = _aggregate(g, part)
        label = [0] * after.n
        for i in range(g.n):
            label[new[i]] = comm[i]
        index: dict[int, int] = {}
        label = [index.setdefault(c, len(index)) for c in label]
        home = [new[h] for h in home]
        if after.n == g.n and not moved:
            comm = label
            break
        g, comm = after, label
    flat = _split_loose(n, links, [comm[h] for h in home])
    least: dict[int, int] = {}
    for i in range(n):
        least.setdefault(flat[i], i)
    return {names[i]: names[least[flat[i]]] for i in range(n)}


def parts(nodes, edges, m: float, resolution: float, max_comm_size: int | None, seed: int, quality: str) -> list:
    """One level over a pack of a larger graph: the part (an id) of each row of ``nodes`` (id, o, i, size).

    ``nodes`` is sorted by id and has the strengths of the whole graph; ``edges`` (src_id, dst_id, w) are those inside the pack.
    """
    names = nodes["id"].tolist()
    at = {x: i for i, x in enumerate(names)}
    links: list[dict[int, float]] = [{} for _ in names]
    for s, d, x in zip(edges["src_id"].tolist(), edges["dst_id"].tolist(), edges["w"].tolist()):
        i, j = at[s], at[d]
        links[i][j] = links[i].get(j, 0.0) + x
        links[j][i] = links[j].get(i, 0.0) + x
    g, rule = _Level(links, nodes["o"].tolist(), nodes["i"].tolist(), nodes["size"].tolist()), (quality == "cpm", resolution, m)
    rng = random.Random(f"{seed}:{names[0]}")
    comm, order = list(range(g.n)), list(range(g.n))
    rng.shuffle(order)
    _move(g, comm, order, rule, max_comm_size)
    rng.shuffle(order)
    part = _refine(g, comm, order, rule)
    if len(set(part)) == g.n:
        part = _split_loose(g.n, links, comm)
    return [names[p] for p in part]


def modularity(src: list, dst: list, w: list, labels: dict, m: float | None = None, resolution: float = 1.0) -> float:
    """Directed modularity of a labelling."""
    m = sum(w) if m is None else m
    if not m:
        return 0.0
    inside, out, inn = 0.0, {}, {}
    for s, d, x in zip(src, dst, w):
        inside += x if labels[s] == labels[d] else 0
        out[labels[s]] = out.get(labels[s], 0.0) + x
        inn[labels[d]] = inn.get(labels[d], 0.0) + x
    return inside / m - resolution * sum(v * inn.get(c, 0.0) for c, v in out.items()) / m / m
