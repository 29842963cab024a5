"""The balancing rounds in plain Python over raw rows: every figure is counted directly, nothing is kept between rounds.

Slow and simple on purpose; the engine's runs are held against it.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import log2


@dataclass(frozen=True)
class Box:
    ident: int
    machine: int
    x0: int
    y0: int
    x1: int
    y1: int


def inside(p, b) -> bool:
    return b.x0 <= p[1] <= b.x1 and b.y0 <= p[2] <= b.y1


def meets(q, b) -> bool:
    return q[1] <= b.x1 and q[3] >= b.x0 and q[2] <= b.y1 and q[4] >= b.y0


class World:
    """Points (rnd, cx, cy) and queries (rnd, cx0, cy0, cx1, cy1)."""

    def __init__(self, points, queries, decay=0.5):
        self.points, self.queries, self.decay = points, queries, decay

    def stats(self, box, rnd):
        """(faded points, queries, recent arrivals, fresh points) of a rectangle."""
        held = [p for p in self.points if p[0] <= rnd and inside(p, box)]
        over = [q for q in self.queries if q[0] <= rnd and meets(q, box)]
        n = sum(self.decay ** (rnd - p[0]) for p in held)
        fresh = sum(p[0] == rnd for p in held)
        return n, len(over), fresh + sum(q[0] == rnd for q in over), fresh

    def cost(self, box, rnd):
        n, q, r, _ = self.stats(box, rnd)
        return n * q * r

    def work(self, box, rnd):
        """Queries over the cells of a rectangle's fresh points."""
        return sum(sum(q[0] <= rnd and meets(q, Box(0, 0, p[1], p[2], p[1], p[2])) for q in self.queries) for p in self.points if p[0] == rnd and inside(p, box))

    def live(self, rnd):
        return sum(q[0] <= rnd for q in self.queries)


def judge(rnd, strategy, loads, arrivals, live, capacity, held, memory=None):
    top, total = max(loads), sum(loads)
    accept = 1.0 if capacity is None or top <= 0 else min(1.0, capacity / top)
    if memory is not None and held > memory:
        accept = 0.0
    return {
        "rnd": rnd, "strategy": strategy, "arrivals": arrivals, "live_queries": live, "max_load": top, "mean_load": total / len(loads), "min_load": min(loads),
        "accept": accept, "processed": accept * arrivals, "units": live * accept * arrivals, "latency": sum(x * x for x in loads) / total if total else 0.0, "held": held,
    }


def static(world, boxes, machines, rounds, strategy, capacity=None, executor="scan", memory=None):
    """``rounds``: how many, or a range of them."""
    out = []
    for rnd in range(rounds) if isinstance(rounds, int) else rounds:
        loads, most = [], 0
        for m in range(machines):
            own = [(world.stats(b, rnd), world.work(b, rnd) if executor == "index" else 0) for b in boxes if b.machine == m]
            held = sum(s[1] for s, _ in own)
            most = max(most, held)
            if executor == "scan":
                loads.append(float(sum(s[3] * s[1] for s, _ in own)))
            else:
                loads.append(sum(s[3] for s, _ in own) * log2(1 + held) + sum(w for _, w in own))
        out.append(judge(rnd, strategy, loads, sum(p[0] == rnd for p in world.points), world.live(rnd), capacity, most, memory))
    return out


def replicated(world, side, machines, rounds, capacity=None, executor="scan", memory=None):
    out, space = [], Box(0, 0, 0, 0, side - 1, side - 1)
    for rnd in range(rounds):
        fresh, live = sum(p[0] == rnd for p in world.points), world.live(rnd)
        work = world.work(space, rnd) if executor == "index" else 0
        mine = [fresh // machines + (m < fresh % machines) for m in range(machines)]
        loads = [float(x * live) if executor == "scan" else x * log2(1 + live) + work / machines for x in mine]
        out.append(judge(rnd, "replicated", loads, fresh, live, capacity, live, memory))
    return out


class Automaton:
    """Decision of each round; beta rounds without a flip force one."""

    def __init__(self, beta):
        self.beta, self.at, self.on, self.same, self.last = beta, 0, False, 0, None

    def __call__(self, total):
        if self.last is not None:
            step = 1 if total > self.last else -1
            self.at = min(2, self.at + step)
            if self.same >= self.beta or self.at == -2:
                self.at, self.on, self.same = 0, not self.on, 0
        self.same += 1
        self.last = total
        return self.on


def rebalance(world, boxes, machines, rnd):
    """(boxes, kind, donor, receiver, gap before, gap after, moved boxes) by trying everything."""
    cost = {b.ident: world.cost(b, rnd) for b in boxes}
    load = {m: sum(cost[b.ident] for b in boxes if b.machine == m) for m in range(machines)}
    low = min(range(machines), key=lambda m: (load[m], m))
    fresh = max(b.ident for b in boxes) + 1
    for high in sorted(range(machines), key=lambda m: (-load[m], m)):
        gap = load[high] - load[low]
        if high == low or gap <= 0:
            continue
        own = sorted((b for b in boxes if b.machine == high), key=lambda b: (-cost[b.ident], b.ident))
        taken, total = set(), 0.0
        for b in own:
            if total + cost[b.ident] <= gap / 2:
                total += cost[b.ident]
                if cost[b.ident] > 0:
                    taken.add(b.ident)
                if total == gap / 2:
                    break
        if total > 0:
            out = []
            for b in boxes:
                if b.ident in taken:
                    b, fresh = Box(fresh, low, b.x0, b.y0, b.x1, b.y1), fresh + 1
                out.append(b)
            return out, "subset", high, low, gap, gap - 2 * total, [b for b in out if b not in boxes]
        b = next((b for b in own if (b.x0, b.y0) != (b.x1, b.y1)), None)
        if b is None:
            continue
        options = []
        lines = [(0, y, (b.x0, b.y0, b.x1, y), (b.x0, y + 1, b.x1, b.y1)) for y in range(b.y0, b.y1)] + [(1, x, (b.x0, b.y0, x, b.y1), (x + 1, b.y0, b.x1, b.y1)) for x in range(b.x0, b.x1)]
        for axis, at, one, two in lines:
            c1, c2 = world.cost(Box(0, 0, *one), rnd), world.cost(Box(0, 0, *two), rnd)
            for moved, gone, kept in (("first", c1, c2), ("second", c2, c1)):
                options.append((abs((load[high] - cost[b.ident] + kept) - (load[low] + gone)), axis, moved, at, one, two))
        best = min(options)
        if best[0] < gap:
            pair = [Box(fresh + k, low if best[2] == side else high, *bounds) for k, (side, bounds) in enumerate((("first", best[4]), ("second", best[5])))]
            return [x for x in boxes if x != b] + pair, "split", high, low, gap, best[0], [x for x in pair if x.machine == low]
    return boxes, "none", None, None, 0.0, 0.0, []


def adaptive(world, boxes, machines, rounds, capacity=None, beta=20, policy="lazy", loop="closed", executor="scan", memory=None):
    """(rows, plans) of all rounds; ``plans[r]`` is in force in round r + 1."""
    automaton, rows, plans = Automaton(beta), [], []
    for rnd in range(rounds):
        row = static(world, boxes, machines, range(rnd, rnd + 1), f"adaptive_{policy}_{loop}", capacity, executor, memory)[0]
        total = sum(world.stats(b, rnd)[2] for b in boxes) * (row["accept"] if loop == "closed" else 1.0)
        wanted = automaton(total) if policy == "lazy" else policy == "always"
        row |= {"tiles": len(boxes), "r_total": total, "decision": "rebalance" if wanted else "nothing", "action": "none", "donor": None, "receiver": None, "gap_before": 0.0, "gap_after": 0.0, "moved_queries": 0}
        if wanted:
            boxes, kind, donor, receiver, before, after, moved = rebalance(world, boxes, machines, rnd)
            row |= {"action": kind, "donor": donor, "receiver": receiver, "gap_before": before, "gap_after": after}
            row["moved_queries"] = sum(q[0] <= rnd and meets(q, b) for q in world.queries for b in moved)
        rows.append(row)
        plans.append(boxes)
    return rows, plans
