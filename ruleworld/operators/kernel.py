"""Search and enumeration inside one task: the clause table of a component as flat lists.

A clause is violated when it is false and its weight positive, or true and its weight negative. Costs are pairs of
hard violations and soft cost, compared in that order.
"""

from __future__ import annotations

import heapq
import math
import time
from dataclasses import dataclass
from functools import lru_cache

import numpy as np


@dataclass
class Clauses:
    """Atoms are numbered from 0 in the order of ``ids``; a literal is ``2 * atom + (1 if positive)``."""

    ids: list[int]
    lits: list[list[int]]
    weight: list[float]
    hard: list[int]

    @staticmethod
    def build(rows) -> Clauses:
        """``rows`` of ``(lits, weight, is_hard[, multiplicity])`` with signed atom ids."""
        rows = list(rows)
        ids = sorted({abs(x) for r in rows for x in r[0]})
        place = {a: k for k, a in enumerate(ids)}
        lits = [[2 * place[abs(x)] + (x > 0) for x in r[0]] for r in rows]
        return Clauses(ids, lits, [float(r[1]) for r in rows], [int(r[3] if len(r) > 3 else 1) if r[2] else 0 for r in rows])

    def touching(self) -> list[list[tuple[int, int]]]:
        """Per atom: clause and sign of each literal."""
        out: list[list[tuple[int, int]]] = [[] for _ in self.ids]
        for c, lits in enumerate(self.lits):
            for x in lits:
                out[x >> 1].append((c, x & 1))
        return out

    def cost(self, world) -> tuple[int, float]:
        hard, soft = 0, 0.0
        for c, lits in enumerate(self.lits):
            true = any(world[x >> 1] == (x & 1) for x in lits)
            if true != (self.weight[c] > 0):
                if self.hard[c]:
                    hard += self.hard[c]
                else:
                    soft += abs(self.weight[c])
        return hard, soft


@dataclass
class Walk:
    world: list[int]
    hard: int
    soft: float
    flips: int
    tries: int
    ms: float
    trace: list[tuple[int, int, float, int, float]]  # try, flip, ms, hard, soft
    best_by_part: list[tuple[int, float]] | None = None
    ended: bool = False  # by no cost, by the target, or by what was sent to it: no later try comes


def walk(cl: Clauses, flips: int, tries: int = 1, noise: float = 0.5, policy: str = "listed", seed: int = 0, start=None, seconds: float | None = None, parts: list[int] | None = None, target: tuple[int, float] | None = None, only: int | None = None) -> Walk:
    """The result of ``walking`` without a pause."""
    return _end(walking(cl, flips, tries, noise, policy, seed, start, seconds, parts, target=target, only=only))


def _end(turns) -> Walk:
    while True:
        try:
            next(turns)
        except StopIteration as e:
            return e.value


def take_turns(walks: list, seconds: float | None = None) -> list[Walk]:
    """Results of several ``walking`` generators that go on in turns, a quantum each.

    After ``seconds`` for all of them together, each ends at its next turn with the best it has seen.
    """
    out: list[Walk | None] = [None] * len(walks)
    left, began, late = dict(enumerate(walks)), time.perf_counter(), None
    while left:
        for k, w in list(left.items()):
            try:
                w.send(late)
            except StopIteration as e:
                out[k] = e.value
                del left[k]
        late = True if seconds is not None and time.perf_counter() - began > seconds else None
    return out


def walking(cl: Clauses, flips: int, tries: int = 1, noise: float = 0.5, policy: str = "listed", seed: int = 0, start=None, seconds: float | None = None, parts: list[int] | None = None, quantum: int = 0, target: tuple[int, float] | None = None, only: int | None = None):
    """Restarted random walk with greedy moves; the start counts as a candidate, zero cost ends it.

    A violated clause is picked evenly; with chance ``noise`` one of its atoms at random flips, else the one whose flip
    costs least (ties: the first atom). ``policy`` ``repairing`` looks only at flips that mend the picked clause, where
    there are any. With ``parts`` (component of each atom) the best state is kept for each part on its own.

    A generator that returns a ``Walk``. With a ``quantum`` it pauses after so many flips, each time; what is sent to it
    tells whether to end there. A cost of ``target`` or less ends it. With ``only`` it makes that try alone, the same that
    it is after tries that ran to their end.
    """
    if policy not in ("listed", "repairing"):
        raise ValueError(f"unknown policy {policy!r}")
    chance, began = np.random.default_rng(seed), time.perf_counter()
    # equal numbers are one object and an atom's places lie together: a large component's walk waits for memory, not for arithmetic
    touch, n = [np.array([2 * c + s for c, s in x], np.int64).tolist() for x in cl.touching()], len(cl.ids)
    lits, weight, hard, same = cl.lits, cl.weight, cl.hard, {}
    up, price = [w > 0 for w in weight], [same.setdefault(p, p) for p in (0.0 if h else abs(w) for w, h in zip(weight, hard, strict=True))]
    best, best_world, trace, done, stop, ended = (math.inf, math.inf), [0] * n, [], 0, False, False
    part_of = [parts[x[0] >> 1] for x in lits] if parts else None
    n_parts = max(parts) + 1 if parts else 0
    part_best = [(math.inf, math.inf)] * n_parts
    part_world = [0] * n
    members: list[list[int]] = [[] for _ in range(n_parts)]
    for a, p in enumerate(parts or ()):
        members[p].append(a)
    pick = [[x >> 1 for x in c] for c in lits]
    t = -1
    for t in range(max(1, tries)):
        world = [int(x) for x in start] if start is not None and t == 0 else chance.integers(0, 2, n).tolist()
        if only is not None and t != only:
            if t > only:
                t -= 1
                break
            _pass_by(chance, flips)
            continue
        true = [sum(world[x >> 1] == (x & 1) for x in c) for c in lits]
        bad, where = [], [-1] * len(lits)
        now_hard, now_soft = 0, 0.0
        part_now = [[0, 0.0] for _ in range(n_parts)]
        for c in range(len(lits)):
            if (true[c] > 0) != up[c]:
                where[c] = len(bad)
                bad.append(c)
                now_hard += hard[c]
                now_soft += price[c]
                if part_of:
                    own = part_now[part_of[c]]
                    own[0] += hard[c]
                    own[1] += price[c]

        def keep(changed):
            for p in changed:
                own = (part_now[p][0], round(part_now[p][1], 9))
                if own < part_best[p]:
                    part_best[p] = own
                    for a in members[p]:
                        part_world[a] = world[a]

        def delta(a):
            dh, ds = 0, 0.0
            v = world[a]
            for x in touch[a]:
                c = x >> 1
                k = true[c]
                if x & 1 == v:
                    if k == 1:
                        if up[c]:
                            dh += hard[c]
                            ds += price[c]
                        else:
                            dh -= hard[c]
                            ds -= price[c]
                elif k == 0:
                    if up[c]:
                        dh -= hard[c]
                        ds -= price[c]
                    else:
                        dh += hard[c]
                        ds += price[c]
            return dh, round(ds, 9)

        keep(range(n_parts))
        cost = (now_hard, round(now_soft, 9))
        if cost < best:
            best, best_world = cost, world[:]
            trace.append((t, done, (time.perf_counter() - began) * 1e3, *cost))
            since: list[int] | None = []  # flips after the best world; None where it is another's, or further away than a copy
        else:
            since = None
        best_hard, best_soft = best
        draws, block = iter(()), 16 if flips > 16 else 512
        for _ in range(flips):
            if not bad or target is not None and best <= target:
                stop = True
                ended = target is not None
                break
            if seconds is not None and done % 1000 == 0 and time.perf_counter() - began > seconds:
                stop = True
                break
            u = next(draws, None)
            if u is None:
                draws = iter(chance.random(3 * block).reshape(-1, 3).tolist())
                block = 496 if block == 16 else 512  # the first two make one of 512, which short walks do not draw
                u = next(draws)
            c = bad[int(u[0] * len(bad))]
            atoms = pick[c]
            if policy == "repairing" and weight[c] < 0:
                atoms = [x >> 1 for x in lits[c] if world[x >> 1] == (x & 1)]
            if len(atoms) == 1:
                a = atoms[0]
            elif u[1] < noise:
                a = atoms[int(u[2] * len(atoms))]
            else:
                a = min(atoms, key=lambda x: (delta(x), x))
            v = world[a]
            world[a] = 1 - v
            for x in touch[a]:
                c = x >> 1
                k = true[c]
                if x & 1 == v:
                    true[c] = k - 1
                    if k != 1:
                        continue
                    broken = up[c]
                else:
                    true[c] = k + 1
                    if k:
                        continue
                    broken = not up[c]
                if broken:
                    where[c] = len(bad)
                    bad.append(c)
                    now_hard += hard[c]
                    now_soft += price[c]
                else:
                    last = bad.pop()
                    if last != c:
                        bad[where[c]] = last
                        where[last] = where[c]
                    where[c] = -1
                    now_hard -= hard[c]
                    now_soft -= price[c]
                if part_of:
                    own, sign = part_now[part_of[c]], 1 if broken else -1
                    own[0] += sign * hard[c]
                    own[1] += sign * price[c]
            done += 1
            if since is not None:
                if len(since) < n:
                    since.append(a)
                else:
                    since = None
            if now_hard < best_hard or now_hard == best_hard and now_soft < best_soft:
                cost = (now_hard, round(now_soft, 9))
                if cost < best:
                    best = best_hard, best_soft = cost
                    trace.append((t, done, (time.perf_counter() - began) * 1e3, *cost))
                    if since is None:
                        best_world = world[:]
                    else:
                        for x in since:
                            best_world[x] ^= 1
                    since = []
            if parts:
                keep((parts[a],))
            if quantum and done % quantum == 0 and (yield):
                stop = ended = True
                break
        if ended or stop and best == (0, 0.0):
            break
        if seconds is not None and time.perf_counter() - began > seconds:
            break
    ms = (time.perf_counter() - began) * 1e3
    if parts:
        total = sum(b[0] for b in part_best), round(sum(b[1] for b in part_best), 9)
        return Walk(part_world, *total, done, t + 1, ms, trace, part_best)
    return Walk(best_world, *best, done, t + 1, ms, trace, ended=bool(ended or stop and best == (0, 0.0)))


def _pass_by(chance, flips: int) -> None:
    """Take from ``chance`` what a try of so many flips draws."""
    drawn, block = 0, 16 if flips > 16 else 512
    while drawn < flips:
        chance.random(3 * block)
        drawn, block = drawn + block, 496 if block == 16 else 512


# Enumeration ---------------------------------------------------------------------------------------------------------


def all_costs(cl: Clauses, most: int = 20) -> tuple[np.ndarray, np.ndarray]:
    """Hard and soft cost of every world; bit k of a world's number is the value of atom k."""
    n = len(cl.ids)
    if n > most:
        raise ValueError(f"{n} atoms are too many to enumerate (at most {most})")
    worlds = np.arange(1 << n)
    hard, soft = np.zeros(1 << n, np.int64), np.zeros(1 << n)
    for lits, w, h in zip(cl.lits, cl.weight, cl.hard, strict=True):
        true = np.zeros(1 << n, bool)
        for x in lits:
            true |= (worlds >> (x >> 1) & 1) == (x & 1)
        bad = ~true if w > 0 else true
        if h:
            hard += h * bad
        else:
            soft += abs(w) * bad
    return hard, soft


def optimum(cl: Clauses) -> tuple[int, float, int]:
    """Least hard and soft cost, and the number of worlds that have it."""
    hard, soft = all_costs(cl)
    h = hard.min()
    s = soft[hard == h].min()
    return int(h), float(s), int(((hard == h) & (soft <= s + 1e-9)).sum())


def least_cost(cl: Clauses, width: int = 12) -> tuple[int, float] | None:
    """Least hard and soft cost by eliminating one atom after another; None where more than ``width`` others would meet in one."""
    return _least(tuple(map(tuple, cl.lits)), tuple(cl.weight), tuple(cl.hard), width)


@lru_cache(maxsize=20_000)
def _least(lits, weight, hard, width):
    tables: dict[int, tuple[list[int], np.ndarray, np.ndarray]] = {}
    of: dict[int, set[int]] = {}  # tables of each atom

    def put(k, atoms, h, s):
        tables[k] = atoms, h, s
        for a in atoms:
            of.setdefault(a, set()).add(k)

    for k, (c, w, n) in enumerate(zip(lits, weight, hard, strict=True)):
        false = {x >> 1: 1 - (x & 1) for x in c}  # the setting that makes every literal false
        atoms = sorted(false)
        if len(atoms) > width + 1:
            return None
        true = np.ones((2,) * len(atoms), bool)
        if not any(x ^ 1 in c for x in c):
            true[tuple(false[a] for a in atoms)] = False
        bad = true != (w > 0)
        put(k, atoms, (n if n else 0) * bad, (0.0 if n else abs(w)) * bad)
    near = {a: set().union(*(tables[k][0] for k in ks)) - {a} for a, ks in of.items()}
    heap = [(len(v), a) for a, v in near.items()]
    heapq.heapify(heap)
    base_hard, base_soft, fresh = 0, 0.0, len(lits)
    while heap:
        n, a = heapq.heappop(heap)
        if a not in near or n != len(near[a]):
            continue
        if n > width:
            return None
        over = sorted([a, *near[a]])
        h, s = np.zeros((1,) * len(over), np.int64), np.zeros((1,) * len(over))
        for k in of.pop(a):
            atoms, th, ts = tables.pop(k)
            shape = [2 if x in atoms else 1 for x in over]
            h, s = h + th.reshape(shape), s + ts.reshape(shape)
            for x in atoms:
                if x != a:
                    of[x].discard(k)
        at = over.index(a)
        (h0, h1), (s0, s1) = np.moveaxis(h, at, 0), np.moveaxis(s, at, 0)
        up = (h1 < h0) | (h1 == h0) & (s1 < s0)
        h, s = np.where(up, h1, h0), np.where(up, s1, s0)
        over.remove(a)
        if over:
            put(fresh, over, h, s)
            fresh += 1
        else:
            base_hard, base_soft = base_hard + int(h), base_soft + float(s)
        mine = near.pop(a)
        for x in mine:
            near[x] = (near[x] | mine) - {a, x}
            heapq.heappush(heap, (len(near[x]), x))
    return base_hard, round(base_soft, 9)


def exact_marginals(cl: Clauses) -> tuple[np.ndarray, float]:
    """Chance of each atom, and the logarithm of the partition sum, over worlds without hard violations."""
    hard, soft = all_costs(cl)
    ok = hard == 0
    if not ok.any():
        raise ValueError("hard rules cannot all hold")
    p = np.where(ok, np.exp(-(soft - soft[ok].min())), 0.0)
    worlds = np.arange(len(p))
    z = p.sum()
    return np.array([p[(worlds >> k & 1) == 1].sum() / z for k in range(len(cl.ids))]), float(math.log(z) - soft[ok].min())


# Step chains ---------------------------------------------------------------------------------------------------------


def step_chances(cl: Clauses, world: int, policy: str, noise: float = 0.5) -> dict[int, float]:
    """Chance of each next world (by its number) in one step from a world with a violated clause."""
    n = len(cl.ids)
    value = [world >> k & 1 for k in range(n)]
    bad = [c for c in range(len(cl.lits)) if any(value[x >> 1] == (x & 1) for x in cl.lits[c]) != (cl.weight[c] > 0)]
    out: dict[int, float] = {}
    for c in bad:
        atoms = [x >> 1 for x in cl.lits[c]]
        if policy == "repairing" and cl.weight[c] < 0:
            true = [x >> 1 for x in cl.lits[c] if value[x >> 1] == (x & 1)]
            atoms = true if len(true) == 1 else atoms if not true else true
        scored = []
        for a in atoms:
            value[a] ^= 1
            scored.append((cl.cost(value), a))
            value[a] ^= 1
        greedy = min(scored)[1]
        for a in atoms:
            out[world ^ 1 << a] = out.get(world ^ 1 << a, 0.0) + noise / len(atoms) / len(bad)
        out[world ^ 1 << greedy] = out.get(world ^ 1 << greedy, 0.0) + (1 - noise) / len(bad)
    return out


def step_profile(cl: Clauses, policy: str = "listed", noise: float = 0.5) -> tuple[float, float, float]:
    """``(a, b, optimum)``: least violations times chance to rise on optima, largest of violations times chance to fall to one.

    b: over optima, min of v(x) * chance that the step leaves the optimal set; a: over worlds one flip from an optimum, max of
    v(x) * chance that the step enters it.
    """
    hard, soft = all_costs(cl)
    best = min(zip(hard, soft, strict=True))
    good = {k for k in range(len(hard)) if (hard[k], round(soft[k], 9)) == (best[0], round(best[1], 9))}

    def v(k):
        value = [k >> j & 1 for j in range(len(cl.ids))]
        return sum(any(value[x >> 1] == (x & 1) for x in lits) != (w > 0) for lits, w in zip(cl.lits, cl.weight, strict=True))

    rise, fall = math.inf, 0.0
    for k in good:
        moves = step_chances(cl, k, policy, noise)
        rise = min(rise, v(k) * sum(p for to, p in moves.items() if to not in good))
        for j in range(len(cl.ids)):
            near = k ^ 1 << j
            if near not in good:
                fall = max(fall, v(near) * sum(p for to, p in step_chances(cl, near, policy, noise).items() if to in good))
    return fall, rise, float(best[1])


def hitting_time(cl: Clauses, policy: str = "listed", noise: float = 0.5, exact: bool = True, runs: int = 400, flips: int = 10**5, seed: int = 0) -> tuple[float, float]:
    """Expected steps to the first optimum from an even start, and from the worst one, by a linear system.

    Not ``exact``: the mean and the largest number of steps of ``runs`` walks; a walk that has not got there within
    ``flips`` counts as that many. The optimum is known by enumeration (at most 20 atoms) in both.
    """
    if not exact:
        hard, soft, _ = optimum(cl)
        steps = []
        for k in range(runs):
            w = _end(walking(cl, flips, 1, noise, policy, seed + k, target=(hard, round(soft, 9))))
            got = [t[1] for t in w.trace if (t[3], round(t[4], 9)) <= (hard, round(soft, 9))]
            steps.append(got[0] if got else flips)
        return float(np.mean(steps)), float(max(steps))
    hard, soft = all_costs(cl, 12)
    best = min(zip(hard, soft, strict=True))
    rest = [k for k in range(len(hard)) if hard[k] > best[0] or soft[k] > best[1] + 1e-9]
    place = {k: i for i, k in enumerate(rest)}
    m = np.eye(len(rest))
    for k, i in place.items():
        for to, p in step_chances(cl, k, policy, noise).items():
            if to in place:
                m[i, place[to]] -= p
    t = np.linalg.solve(m, np.ones(len(rest))) if rest else np.zeros(0)
    return float(t.sum() / len(hard)), float(t.max()) if len(t) else 0.0


# Sampling ------------------------------------------------------------------------------------------------------------


def sample_sat(n: int, need: list[list[int]], chance, flips: int, start, walk_prob: float = 0.5, temperature: float = 0.5):
    """A nearly even draw from the worlds that satisfy all clauses of ``need``: walking moves mixed with annealing ones.

    None if none is found within ``flips``.
    """
    world = list(start)
    fixed: dict[int, int] = {}
    work = [c for c in need if len(c) == 1]
    while work:  # units first
        x = work.pop()[0]
        if fixed.get(x >> 1, x & 1) != (x & 1):
            return None
        if x >> 1 in fixed:
            continue
        fixed[x >> 1] = x & 1
        for c in need:
            left = [y for y in c if y >> 1 not in fixed]
            if len(left) == 1 and len(c) > 1 and not any(fixed.get(y >> 1) == (y & 1) for y in c):
                work.append(left)
    rest = []
    for c in need:
        if any(fixed.get(y >> 1) == (y & 1) for y in c):
            continue
        left = [y for y in c if y >> 1 not in fixed]
        if not left:
            return None
        rest.append(left)
    for a in range(n):
        world[a] = fixed[a] if a in fixed else int(chance.random() < 0.5)
    free = sorted({y >> 1 for c in rest for y in c})
    if not free:
        return world
    touch: dict[int, list[int]] = {a: [] for a in free}
    for k, c in enumerate(rest):
        for y in c:
            touch[y >> 1].append(k)

    def broken(ks):
        return [k for k in ks if not any(world[y >> 1] == (y & 1) for y in rest[k])]

    for _ in range(flips):
        bad = broken(range(len(rest)))
        if not bad:
            return world
        if chance.random() < walk_prob:
            c = rest[bad[int(chance.random() * len(bad))]]
            if chance.random() < 0.5:
                a = c[int(chance.random() * len(c))] >> 1
            else:
                def harm(a):
                    was = len(broken(touch[a]))
                    world[a] ^= 1
                    now = len(broken(touch[a]))
                    world[a] ^= 1
                    return now - was

                a = min((y >> 1 for y in c), key=lambda a: (harm(a), a))
            world[a] ^= 1
        else:
            a = free[int(chance.random() * len(free))]
            was = len(broken(touch[a]))
            world[a] ^= 1
            worse = len(broken(touch[a])) - was
            if worse > 0 and chance.random() >= math.exp(-worse / temperature):
                world[a] ^= 1
    return None if broken(range(len(rest))) else world


def mc_sat(cl: Clauses, samples: int = 1000, burn_in: int = 100, seed: int = 0, flips: int = 200) -> tuple[np.ndarray, int]:
    """Slice-sampled chance of each atom, and the number of steps in which no new state was found."""
    chance = np.random.default_rng(seed)
    hard = [c for c, h in zip(cl.lits, cl.hard, strict=True) if h]
    begin = walk(Clauses(cl.ids, cl.lits, cl.weight, cl.hard), 20 * len(cl.ids) + 100, 5, seed=seed)
    if begin.hard:
        raise ValueError("no start without hard violations was found")
    world, total, stalls = begin.world, np.zeros(len(cl.ids)), 0
    for step in range(burn_in + samples):
        need = [list(c) for c in hard]
        for c, w, h in zip(cl.lits, cl.weight, cl.hard, strict=True):
            if h:
                continue
            true = any(world[x >> 1] == (x & 1) for x in c)
            if true == (w > 0) and chance.random() < 1 - math.exp(-abs(w)):
                need += [list(c)] if w > 0 else [[x ^ 1] for x in c]
        new = sample_sat(len(cl.ids), need, chance, flips, world)
        if new is None:
            stalls += 1
        else:
            world = new
        if step >= burn_in:
            total += world
    return total / samples, stalls
