"""Temporal maximum flow of one flow's payments (Dinic's algorithm on integers).

Payments are split nodes that carry at most their amount; money goes from payment to payment along edges of the temporal
graph. Sources are payments of dispense accounts, targets payments to sink accounts. The network has
no cycle as time rises along every edge. With ``hold="unbounded"`` an account may keep money for
any time: accounts become chains of their instants instead.
"""

from __future__ import annotations

from collections import deque


class Network:
    def __init__(self):
        self.to: list[int] = []
        self.cap: list[int] = []
        self.out: list[list[int]] = []

    def node(self) -> int:
        self.out.append([])
        return len(self.out) - 1

    def arc(self, a: int, b: int, cap: int) -> None:
        for x, y, c in ((a, b, cap), (b, a, 0)):
            self.out[x].append(len(self.to))
            self.to.append(y)
            self.cap.append(c)

    def _levels(self, s: int, t: int) -> list[int] | None:
        level, queue = [-1] * len(self.out), deque([s])
        level[s] = 0
        while queue:
            x = queue.popleft()
            for e in self.out[x]:
                if self.cap[e] and level[self.to[e]] < 0:
                    level[self.to[e]] = level[x] + 1
                    queue.append(self.to[e])
        return level if level[t] >= 0 else None

    def max_flow(self, s: int, t: int) -> int:
        total = 0
        while (level := self._levels(s, t)) is not None:
            at = [0] * len(self.out)
            while True:
                path, x = [], s  # walk down level by level, stepping back where it ends
                while x != t:
                    while at[x] < len(self.out[x]):
                        e = self.out[x][at[x]]
                        if self.cap[e] and level[self.to[e]] == level[x] + 1:
                            break
                        at[x] += 1
                    else:
                        if x == s:
                            break
                        e = path.pop()
                        x = self.to[e ^ 1]
                        at[x] += 1
                        continue
                    path.append(e)
                    x = self.to[e]
                if x != t:
                    break
                push = min(self.cap[e] for e in path)
                for e in path:
                    self.cap[e] -= push
                    self.cap[e ^ 1] += push
                total += push
        return total


def roles(txns: list[tuple]) -> tuple[set, set]:
    """Dispense and sink accounts of (id, us, payer, payee, amount) rows."""
    pay, get = {t[2] for t in txns}, {t[3] for t in txns}
    return pay - get, get - pay


def windowed(txns: list[tuple], edges: list[tuple], ends: tuple[set, set] | None = None) -> int:
    """Money that can go from dispense to sink accounts along the given (src_id, dst_id) edges."""
    first, last = ends or roles(txns)
    net, inn, out = Network(), {}, {}
    s, t = net.node(), net.node()
    big = 1 + sum(x[4] for x in txns)
    for i, _, a, b, amount in txns:
        inn[i], out[i] = net.node(), net.node()
        net.arc(inn[i], out[i], amount)
        if a in first:
            net.arc(s, inn[i], big)
        if b in last:
            net.arc(out[i], t, big)
    for i, j in edges:
        if i in out and j in inn:
            net.arc(out[i], inn[j], big)
    return net.max_flow(s, t)


def unbounded(txns: list[tuple], ends: tuple[set, set] | None = None) -> int:
    """The same where accounts may hold money for ever: received strictly before it is sent."""
    first, last = ends or roles(txns)
    net = Network()
    s, t = net.node(), net.node()
    big = 1 + sum(x[4] for x in txns)
    times: dict[int, set] = {}
    for _, us, a, b, _ in txns:
        times.setdefault(a, set()).add((us, 0))  # what can be sent at us
        times.setdefault(b, set()).add((us, 1))  # what has come by us, for later
    place: dict[tuple, int] = {}
    for acct, when in times.items():
        before = None
        for key in sorted(when):
            place[acct, key] = net.node()
            if before is not None:
                net.arc(before, place[acct, key], big)
            before = place[acct, key]
        if acct in first:
            net.arc(s, place[acct, min(when)], big)
        if acct in last:
            net.arc(before, t, big)
    for _, us, a, b, amount in txns:
        net.arc(place[a, (us, 0)], place[b, (us, 1)], amount)
    return net.max_flow(s, t)
