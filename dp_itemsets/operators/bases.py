"""Basis sets: small sets of items that cover the frequent itemsets, and how they are built.

All of this is driver work on private outputs (items and pairs that were
already drawn); no function here reads transactions.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np

Itemset = frozenset


@dataclass(frozen=True)
class BasisSet:
    bases: tuple[tuple[str, ...], ...]

    @classmethod
    def of(cls, bases: Iterable[Iterable[str]]) -> BasisSet:
        return cls(tuple(tuple(sorted(set(b))) for b in bases if set(b)))

    @classmethod
    def single(cls, items: Iterable[str]) -> BasisSet:
        """One basis of all frequent items: covers everything, at width 1."""
        return cls.of([items])

    @classmethod
    def blocks(cls, items: Iterable[str], size: int) -> BasisSet:
        items = list(items)
        return cls.of(items[k : k + size] for k in range(0, len(items), size))

    @classmethod
    def from_cliques(cls, items: Iterable[str], pairs: Iterable[tuple[str, str]]) -> BasisSet:
        """Maximal cliques of the pair graph, isolated items included: covers every itemset whose pairs are all frequent."""
        return cls.of(maximal_cliques(pair_graph(items, pairs), 1))

    def __iter__(self) -> Iterator[tuple[str, ...]]:
        return iter(self.bases)

    def __len__(self) -> int:
        return len(self.bases)

    @property
    def width(self) -> int:
        return len(self.bases)

    @property
    def length(self) -> int:
        return max(map(len, self.bases), default=0)

    @property
    def items(self) -> list[str]:
        return sorted({i for b in self.bases for i in b})

    def covers(self, itemset: Iterable[str]) -> bool:
        wanted = set(itemset)
        return any(wanted <= set(b) for b in self.bases)

    def uncovered(self, itemsets: Iterable[Iterable[str]]) -> list[tuple[str, ...]]:
        return [tuple(s) for s in itemsets if not self.covers(s)]

    def merged(self, i: int, j: int) -> BasisSet:
        """Two bases as their union: still covers all it covered, with one basis less."""
        rest = [b for k, b in enumerate(self.bases) if k not in (i, j)]
        return BasisSet.of([*rest, {*self.bases[i], *self.bases[j]}])

    def candidates(self) -> set[frozenset]:
        """All non-empty subsets of the bases."""
        out: set[frozenset] = set()
        for b in self.bases:
            out.update(frozenset(x for p, x in enumerate(b) if mask >> p & 1) for mask in range(1, 1 << len(b)))
        return out


def pair_graph(items: Iterable[str], pairs: Iterable[tuple[str, str]]) -> dict[str, set[str]]:
    graph: dict[str, set[str]] = {i: set() for i in items}
    for a, b in pairs:
        if a != b:
            graph.setdefault(a, set()).add(b)
            graph.setdefault(b, set()).add(a)
    return graph


def maximal_cliques(graph: dict[str, set[str]], min_size: int = 2) -> list[frozenset]:
    """All inclusion-maximal cliques of a size or more, by branching without the neighbours of a pivot."""
    out: list[frozenset] = []
    todo: list[tuple[frozenset, set, set]] = [(frozenset(), set(graph), set())]
    while todo:
        clique, open_, closed = todo.pop()
        if not open_ and not closed:
            if len(clique) >= min_size:
                out.append(clique)
            continue
        if not open_:
            continue
        pivot = max(sorted(open_ | closed), key=lambda v: len(graph[v] & open_))
        for v in sorted(open_ - graph[pivot]):
            todo.append((clique | {v}, open_ & graph[v], closed & graph[v]))
            open_ = open_ - {v}
            closed = closed | {v}
    return sorted(out, key=lambda c: (-len(c), sorted(c)))


def split_long(cliques: Iterable[frozenset], longest: int) -> list[frozenset]:
    """Cliques above the length cap as unions of pairs of blocks: every pair of items stays covered, larger sets may not."""
    out: list[frozenset] = []
    for c in cliques:
        if len(c) <= longest:
            out.append(c)
            continue
        items, half = sorted(c), max(longest // 2, 1)
        parts = [items[k : k + half] for k in range(0, len(items), half)]
        out += [frozenset(a + b) for k, a in enumerate(parts) for b in parts[k + 1 :]]
    return out


def group_leftovers(items: Iterable[str], size: int = 3) -> list[frozenset]:
    """Items without a pair, as few groups as possible."""
    items = sorted(items)
    return [frozenset(items[k : k + size]) for k in range(0, len(items), size)]


def grouping_factor(size: int) -> float:
    """Error variance of single items in bases of a size, against one basis an item."""
    return 2.0 ** (size - 1) / size**2


def error_variance(length: int, size: int, width: int, eps: float, n: float = 1.0) -> float:
    """Of one estimate: 2^(length - size) bins of variance 2 (width / (eps n))^2."""
    return 2.0 ** (length - size + 1) * (width / (eps * n)) ** 2


def worst_error_variance(bases: BasisSet, eps: float, n: float = 1.0) -> float:
    return 2.0**bases.length * (bases.width / (eps * n)) ** 2


def _precision(bases: list[frozenset], wanted: list[frozenset]) -> np.ndarray:
    """(wanted, bases): inverse of the variance weight where a basis covers a set, else 0."""
    return np.array([[2.0 ** -(len(b) - len(x) + 1) if x <= b else 0.0 for b in bases] for x in wanted]).reshape(len(wanted), len(bases))


def average_error_variance(bases: BasisSet | list[frozenset], wanted: Iterable[Iterable[str]], eps: float = 1.0, n: float = 1.0) -> float:
    """Mean over the wanted sets of the variance of their fused estimates; infinite if one isn't covered."""
    sets, own = [frozenset(x) for x in wanted], [frozenset(b) for b in bases]
    total = _precision(own, sets).sum(axis=1)
    if not sets:
        return 0.0
    if not (total > 0).all():
        return float("inf")
    return float((len(own) / (eps * n)) ** 2 * (1 / total).mean())


def build_bases(
    items: Iterable[str], pairs: Iterable[tuple[str, str]], longest: int = 12, leftover_size: int = 3, objective: str = "items_and_pairs", merge: bool = True, dissolve: bool = True,
) -> BasisSet:
    """Bases that cover all given items and pairs, with low mean error variance.

    Cliques of the pair graph are merged two at a time while that lowers the
    mean variance over the objective's sets; then groups of left-over items are
    dissolved into the smallest other bases while that does.
    """
    items, pairs = sorted(set(items)), sorted({tuple(sorted(p)) for p in pairs if p[0] != p[1]})
    paired = {i for p in pairs for i in p}
    lone = [i for i in items if i not in paired]
    single = items if objective == "items_and_pairs" else lone
    if objective not in ("items_and_pairs", "leftover_items_and_pairs"):
        raise ValueError("unknown objective")
    wanted = [frozenset([i]) for i in sorted({*single, *(paired if objective == "items_and_pairs" else ())})] + [frozenset(p) for p in pairs]
    first = [*dict.fromkeys(split_long(maximal_cliques(pair_graph(paired, pairs), 2), longest))]
    second = group_leftovers(lone, min(leftover_size, longest))
    if merge and wanted:
        first = _merge(first, second, wanted, longest)
    if dissolve and wanted:
        first, second = _dissolve(first, second, wanted, longest)
    return BasisSet.of([*first, *second])


#: Relative distance from the best within which merges are compared in full.
NEAR = 1e-9


def _merge(first: list[frozenset], second: list[frozenset], wanted: list[frozenset], longest: int) -> list[frozenset]:
    """Merges of two bases, the best one first.

    A merge moves the precision of no sets but those that the union covers.  So
    each round looks at these alone, for all merges at once, and compares in
    full those that come within NEAR of the best.
    """
    fixed = _precision(second, wanted).sum(axis=1)
    place = {i: k for k, i in enumerate(sorted({i for s in (*first, *wanted) for i in s}))}
    held, sizes = np.zeros((len(wanted), len(place)), np.float32), np.array([len(x) for x in wanted])
    for k, x in enumerate(wanted):
        held[k, [place[i] for i in x]] = 1

    # all bases that there ever were; a merge is numbered by its place in left and right, and has a row in at and moved for each set it covers
    n = len(first)
    names = list(place)
    inside, columns = np.zeros((2 * n, len(place)), np.float32), np.zeros((2 * n, len(wanted)))
    for k, b in enumerate(first):
        inside[k, [place[i] for i in b]] = 1
    columns[:n] = _precision(first, wanted).T
    alive, left, right = list(range(n)), np.zeros(0, np.int64), np.zeros(0, np.int64)
    owner, at, moved = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)

    def covered(unions: np.ndarray) -> np.ndarray:
        return np.where(unions @ held.T == sizes, 2.0 ** -(unions.sum(axis=1, dtype=np.int64)[:, None] - sizes + 1.0), 0.0)

    def add(i: np.ndarray, j: np.ndarray) -> None:
        nonlocal left, right, owner, at, moved
        short = np.concatenate([np.maximum(inside[i[k : k + 4096]], inside[j[k : k + 4096]]).sum(axis=1) <= longest for k in range(0, i.size, 4096)] or [np.zeros(0, bool)])
        i, j = i[short], j[short]
        parts = [(owner, at, moved)]
        for k in range(0, i.size, 4096):
            a, b = i[k : k + 4096], j[k : k + 4096]
            own = covered(np.maximum(inside[a], inside[b]))
            row, some = np.nonzero(own)
            parts.append((row + left.size + k, some, own[row, some] - columns[a[row], some] - columns[b[row], some]))
        owner, at, moved = (np.concatenate(x) for x in zip(*parts, strict=True))
        left, right = np.r_[left, i], np.r_[right, j]

    add(*np.triu_indices(n, 1))
    dead, last = np.zeros(left.size, bool), n
    while len(alive) > 1 and not dead.all():
        total, width = fixed + np.sum([columns[k] for k in alive], axis=0), len(alive) + len(second)
        now, inverse = width**2 * (1 / total).mean(), 1 / total
        rough = inverse.sum() + np.bincount(owner, 1 / (total[at] + moved) - inverse[at], left.size)
        rough[dead] = np.inf
        near, best = np.flatnonzero(rough <= rough.min() * (1 + NEAR)), None
        for p in near[np.lexsort((right[near], left[near]))].tolist():
            i, j = left[p], right[p]
            own = covered(np.maximum(inside[i], inside[j])[None])[0]
            value = (width - 1) ** 2 * (1 / (total - columns[i] - columns[j] + own)).mean()
            if value < (best[0] if best else now * (1 - 1e-12)):
                best = (value, i, j, own)
        if best is None:
            break
        _, i, j, own = best
        dead |= (left == i) | (right == i) | (left == j) | (right == j)
        keep = ~dead[owner]
        owner, at, moved = owner[keep], at[keep], moved[keep]
        alive = [k for k in alive if k not in (i, j)]
        inside[last], columns[last] = np.maximum(inside[i], inside[j]), own
        add(np.array(alive, np.int64), np.full(len(alive), last))
        alive.append(last)
        dead, last = np.r_[dead, np.zeros(left.size - dead.size, bool)], last + 1
    return [frozenset(names[x] for x in np.flatnonzero(inside[k])) for k in alive]


def _dissolve(first: list[frozenset], second: list[frozenset], wanted: list[frozenset], longest: int) -> tuple[list[frozenset], list[frozenset]]:
    def value(a: list[frozenset], b: list[frozenset]) -> float:
        return average_error_variance([*a, *b], wanted)

    while second and len(first) + len(second) > 1:
        now, best = value(first, second), None
        for g in range(len(second)):
            bases = [*first, *(b for k, b in enumerate(second) if k != g)]
            for item in sorted(second[g]):  # each to the smallest basis that has room
                room = [k for k, b in enumerate(bases) if len(b) < longest]
                if not room:
                    break
                at = min(room, key=lambda k: (len(bases[k]), k))
                bases[at] = bases[at] | {item}
            else:
                new = (bases[: len(first)], bases[len(first) :])
                v = value(*new)
                if v < (best[0] if best else now * (1 - 1e-12)):
                    best = (v, *new)
        if best is None:
            break
        first, second = best[1], best[2]
    return first, second
