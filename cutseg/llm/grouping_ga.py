"""A grouping genetic algorithm for bin packing with whole-number sizes.

Items of one size are interchangeable, so an individual is a table of bin
contents (sizes, largest first) with the number of bins that have them.  Its
size depends on the number of different sizes, not of items: a corpus of any
size evolves in bounded memory.
"""

from __future__ import annotations

import random
from bisect import bisect_left, insort
from collections import Counter

#: Bin contents -> number of such bins.
Packing = dict[tuple[int, ...], int]


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """No packing has fewer bins: by volume, and by items over half a bin."""
    volume = -(-sum(s * n for s, n in counts.items()) // capacity)
    return max(volume, sum(n for s, n in counts.items() if 2 * s > capacity))


def best_fit(bins: Packing, items: dict[int, int], capacity: int, order: list[int] | None = None) -> Packing:
    """Put ``items`` (size -> number) one after another, in ``order`` (default:
    largest first), into the fullest bin that has room, or into a new one."""
    done: Counter = Counter()
    by_gap: dict[int, dict[tuple, int]] = {}
    gaps: list[int] = []

    def put(content: tuple, n: int) -> None:
        gap = capacity - sum(content)
        if not gap:
            done[content] += n
            return
        if gap not in by_gap:
            by_gap[gap] = {}
            insort(gaps, gap)
        by_gap[gap][content] = by_gap[gap].get(content, 0) + n

    for content, n in bins.items():
        put(content, n)
    for size in order or sorted(items, reverse=True):
        left = items[size]
        while left:
            i = bisect_left(gaps, size)
            if i == len(gaps):
                each = capacity // size
                full, rest = divmod(left, each)
                if full:
                    put((size,) * each, full)
                if rest:
                    put((size,) * rest, 1)
                break
            gap = gaps[i]
            held = by_gap[gap]
            content = next(iter(held))
            n = held.pop(content)
            if not held:
                del by_gap[gap]
                gaps.pop(i)
            fit = gap // size  # so many go into each of these bins in turn
            whole, rest = divmod(left, fit)
            if whole >= n:
                put(_with(content, size, fit), n)
                left -= n * fit
            else:
                if whole:
                    put(_with(content, size, fit), whole)
                if rest:
                    put(_with(content, size, rest), 1)
                if n - whole - bool(rest):
                    put(content, n - whole - bool(rest))
                left = 0
    for held in by_gap.values():
        for content, n in held.items():
            done[content] += n
    return dict(done)


def _with(content: tuple, size: int, times: int) -> tuple:
    return tuple(sorted(content + (size,) * times, reverse=True))


def bins_of(p: Packing) -> int:
    return sum(p.values())


def fitness(p: Packing, capacity: int) -> tuple[int, float]:
    """Fewer bins first; then bins that are rather full or rather empty."""
    n = bins_of(p)
    return -n, sum(c * (sum(k) / capacity) ** 2 for k, c in p.items()) / max(n, 1)


def crossover(a: Packing, b: Packing, capacity: int, rng: random.Random, fill: float = 0.995, share: float = 0.5) -> Packing:
    """Inject whole well-filled bins of ``b`` into ``a``.

    Bins of ``a`` with an item that came in again are taken apart, least filled
    first; their other items are placed anew by best fit.
    """
    injected = {k: n for k, n in b.items() if sum(k) >= fill * capacity and rng.random() < share}
    child: Packing = {}
    need: Counter = Counter()
    rest = dict(a)
    for content, n in injected.items():
        child[content] = n
        same = min(n, rest.get(content, 0))  # bins that both have just stay
        if same:
            rest[content] -= same
        for size in content:
            need[size] += n - same
    free: Counter = Counter()
    for content in sorted(rest, key=lambda k: (sum(k), k)):
        n, times = rest[content], Counter(content)
        apart = min(n, max((-(-need[s] // m) for s, m in times.items() if need[s] > 0), default=0))
        if apart:
            for s, m in times.items():
                gone = min(need[s], m * apart)
                need[s] -= gone
                free[s] += m * apart - gone
        if n > apart:
            child[content] = child.get(content, 0) + n - apart
    return best_fit(child, +free, capacity)


def mutate(p: Packing, capacity: int, rng: random.Random, share: float = 0.1) -> Packing:
    """Take some bins apart, the least filled always, and place their items
    anew in an order that is nearly by size."""
    kept: Packing = {}
    free: Counter = Counter()
    worst = min(p, key=lambda k: (sum(k), k), default=None)
    for content, n in p.items():
        apart = n if content == worst else sum(rng.random() < share for _ in range(n)) if n < 50 else int(n * share * 2 * rng.random())
        for s in content if apart else ():
            free[s] += apart
        if n > apart:
            kept[content] = n - apart
    order = sorted(free, key=lambda s: -s * rng.uniform(0.9, 1.1))
    return best_fit(kept, free, capacity, order)


def random_packing(counts: dict[int, int], capacity: int, rng: random.Random) -> Packing:
    order = sorted(counts, key=lambda s: -s * rng.uniform(0.6, 1.4))
    return best_fit({}, counts, capacity, order)


def evolve(counts: dict[int, int], capacity: int, seeds: list[Packing], rng: random.Random, population: int = 5, generations: int = 6) -> Packing:
    """Run one island for some generations; its best individual, never worse
    than the best of ``seeds``.  Random packings fill up the first population; a
    generation that meets the lower bound is the last one."""
    bound = lower_bound(counts, capacity)
    key = lambda p: fitness(p, capacity)
    pool = list(seeds)
    while len(pool) < population:
        pool.append(random_packing(counts, capacity, rng))
    for _ in range(generations):
        children = []
        for _ in range(max(1, population // 2)):
            a, b = (max(rng.sample(pool, 2), key=key) for _ in range(2))
            children += [crossover(a, b, capacity, rng), mutate(a, capacity, rng)]
        pool = sorted(pool + children, key=key, reverse=True)[:population]
        if bins_of(pool[0]) <= bound:
            break
    return max(pool, key=key)
