"""Exact functional dependencies from a histogram of overlap masks (driver, small data).

X -> A is violated exactly by pairs whose mask holds X and lacks A.  Two
independent searches over the same histogram must agree: level by level with
pruning, and by inverting the negative cover.
"""

from __future__ import annotations

from collections.abc import Iterable
from itertools import combinations


def violations(hist: dict[int, int], lhs: int, rhs: int) -> int:
    bit = 1 << rhs
    return sum(n for m, n in hist.items() if m & lhs == lhs and not m & bit)


def levelwise(hist: dict[int, int], n_paths: int, max_lhs: int = 3) -> set[tuple[int, int]]:
    """Minimal valid (lhs mask, rhs) with at most max_lhs paths on the left."""
    masks = list(hist)
    found: set[tuple[int, int]] = set()
    every = (1 << n_paths) - 1
    # rest[X]: right sides for which neither X nor a subset of X is known to be valid
    level = {0: every}
    for size in range(max_lhs + 1):
        after: dict[int, int] = {}
        for lhs, rest in level.items():
            if size:
                rest &= ~lhs
            covering = [m for m in masks if m & lhs == lhs]
            lacking = 0
            for m in covering:  # no covering mask at all: lhs is a key and determines everything
                lacking |= ~m & every
            for rhs in bits(rest & ~lacking):
                found.add((lhs, rhs))
            rest &= lacking
            if rest and size < max_lhs:
                after[lhs] = rest
        level = _next_level(after, n_paths)
    return found


def _next_level(level: dict[int, int], n_paths: int) -> dict[int, int]:
    """Join sets that differ in their last path; a right side survives if all subsets leave it open."""
    out: dict[int, int] = {}
    for lhs in level:
        top = lhs.bit_length()
        for p in range(top, n_paths):
            grown = lhs | 1 << p
            subsets = [grown & ~(1 << q) for q in bits(grown)]
            if all(s in level for s in subsets):
                rest = -1
                for s in subsets:
                    rest &= level[s]
                # A subset without an open right side closes all of its supersets.
                if rest & ~grown & ((1 << n_paths) - 1):
                    out[grown] = rest & ((1 << n_paths) - 1)
    return out


def bits(mask: int) -> Iterable[int]:
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def negative_cover(hist: dict[int, int], n_paths: int) -> dict[int, list[int]]:
    """For each right side the maximal masks that lack it."""
    out = {}
    for rhs in range(n_paths):
        lacking = sorted({m for m in hist if not m >> rhs & 1}, key=lambda m: -m.bit_count())
        top: list[int] = []
        for m in lacking:
            if not any(m & t == m for t in top):
                top.append(m)
        out[rhs] = top
    return out


def invert(negatives: dict[int, list[int]], n_paths: int, max_lhs: int = 3) -> set[tuple[int, int]]:
    """Minimal left sides that no negative mask holds: minimal transversals of the complements."""
    every, found = (1 << n_paths) - 1, set()
    for rhs, masks in negatives.items():
        covers = [0]
        for m in masks:
            out_of = every & ~m & ~(1 << rhs)
            hit = [c for c in covers if c & out_of]
            grown = {c | 1 << p for c in covers if not c & out_of for p in bits(out_of) if c.bit_count() < max_lhs}
            covers = hit + [g for g in sorted(grown, key=int.bit_count) if not any(h & g == h for h in hit)]
            covers = _minimal(covers)
        found |= {(c, rhs) for c in covers}
    return found


def _minimal(masks: list[int]) -> list[int]:
    out: list[int] = []
    for m in sorted(set(masks), key=int.bit_count):
        if not any(o & m == o for o in out):
            out.append(m)
    return out


def brute_force(hist: dict[int, int], n_paths: int, max_lhs: int = 3) -> set[tuple[int, int]]:
    found: set[tuple[int, int]] = set()
    for size in range(max_lhs + 1):
        for paths in combinations(range(n_paths), size):
            lhs = sum(1 << p for p in paths)
            for rhs in range(n_paths):
                if not lhs >> rhs & 1 and not any(f & lhs == f and r == rhs for f, r in found) and not violations(hist, lhs, rhs):
                    found.add((lhs, rhs))
    return found


def minimal_keys(hist: dict[int, int], n_paths: int, max_size: int = 3) -> set[int]:
    """Minimal sets of paths on all of which no two documents overlap."""
    found: list[int] = []
    for size in range(1, max_size + 1):
        for paths in combinations(range(n_paths), size):
            x = sum(1 << p for p in paths)
            if not any(f & x == f for f in found) and not any(m & x == x for m in hist):
                found.append(x)
    return set(found)


# -- inference ---------------------------------------------------------------

Fd = tuple[frozenset, str]


def attr_closure(paths: Iterable[str], deps: Iterable[Fd]) -> frozenset:
    """All paths that a set determines."""
    out, deps = set(paths), list(deps)
    moved = True
    while moved:
        moved = False
        for lhs, rhs in deps:
            if rhs not in out and lhs <= out:
                out.add(rhs)
                moved = True
    return frozenset(out)


def implies(deps: Iterable[Fd], dep: Fd) -> bool:
    return dep[1] in attr_closure(dep[0], deps)


def minimal_cover(deps: Iterable[Fd]) -> set[Fd]:
    """Left-reduced and without redundant dependencies."""
    deps = [(frozenset(x), a) for x, a in deps]
    reduced = []
    for lhs, rhs in sorted(deps, key=lambda d: (sorted(d[0]), d[1])):
        for p in sorted(lhs):
            if implies(deps, (lhs - {p}, rhs)):
                lhs = lhs - {p}
        reduced.append((lhs, rhs))
    kept = list(dict.fromkeys(reduced))
    for d in list(kept):
        rest = [k for k in kept if k != d]
        if implies(rest, d):
            kept = rest
    return set(kept)


def equivalent(one: Iterable[Fd], two: Iterable[Fd]) -> bool:
    one, two = list(one), list(two)
    return all(implies(two, d) for d in one) and all(implies(one, d) for d in two)
