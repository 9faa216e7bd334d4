"""Tag-local methods: all of a session's paths stay in it, so one exchange by session is enough for any of them.

A piece is one session in memory; sessions end at every silence longer than the threshold."""

from __future__ import annotations

import bisect
import hashlib
import math
from collections import Counter
from collections.abc import Iterator
from itertools import accumulate

from pathtraces.functions.columns import BASES, PRIMES, SEPARATOR


def uniform(seed: int, *key) -> float:
    """Equal to the column function of that name."""
    text = "|".join(map(str, (seed, *key)))
    return (int(hashlib.md5(text.encode()).hexdigest()[:13], 16) + 0.5) / 2.0**52


class Piece:
    """Vertices in time order, with the places of their successors."""

    def __init__(self, vid: list[int], label: list[str], after: list[list[int]]):
        self.vid, self.label, self.after = vid, label, after
        self._counts: dict[int, list[list[int]]] = {}
        self._lines: dict[tuple[int, int, int], tuple[list[int], list[int], list[int]]] = {}

    @classmethod
    def of(cls, group, delta: int) -> Piece:
        rows = sorted(zip(*(group[c].to_pylist() for c in ("t_first", "vid", "t_last", "label")), strict=True))
        after = []
        for k, (_, _, end, label) in enumerate(rows):
            mine = []
            for j in range(k + 1, len(rows)):
                if rows[j][0] - end > delta:
                    break
                if rows[j][3] != label:
                    mine.append(j)
            after.append(mine)
        return cls([r[1] for r in rows], [r[3] for r in rows], after)

    def counts(self, m: int) -> list[list[int]]:
        """For each vertex, the paths of at most 0, 1, ..., m vertices that start there."""
        if m not in self._counts:
            out: list[list[int]] = [[]] * len(self.vid)
            for k in range(len(self.vid) - 1, -1, -1):
                out[k] = [0] + [1 + sum(out[j][i - 1] for j in self.after[k]) for i in range(1, m + 1)]
            self._counts[m] = out
        return self._counts[m]

    def traces(self, m: int) -> Counter:
        """All traces with their counts, by suffixes."""
        last: list[Counter] = [Counter({label: 1}) for label in self.label]
        total: Counter = Counter()
        for step in last:
            total.update(step)
        for _ in range(m - 1):
            now = []
            for k in range(len(self.vid)):
                mine: Counter = Counter()
                for j in self.after[k]:
                    for t, n in last[j].items():
                        mine[self.label[k] + SEPARATOR + t] += n
                now.append(mine)
                total.update(mine)
            last = now
        return total

    def paths(self, m: int) -> Iterator[list[int]]:
        """Every path, with an explicit stack."""
        stack = [[k] for k in range(len(self.vid))]
        while stack:
            path = stack.pop()
            yield path
            if len(path) < m:
                stack.extend([*path, j] for j in self.after[path[-1]])

    def named(self, path: list[int]) -> tuple[int, str, str]:
        return self.vid[path[0]], "-".join(str(self.vid[k]) for k in path), SEPARATOR.join(self.label[k] for k in path)

    def sample(self, m: int, p: float, seed: int, how: str = "descend") -> Iterator[tuple[int, str, str]]:
        """(start, path, trace); each path with probability p, independently (``printed`` excepted)."""
        c = self.counts(m)
        rest = math.log1p(-p) if p < 1 else -math.inf
        some = lambda n: -math.expm1(n * rest) if n else 0.0  # noqa: E731  probability that any of n is drawn
        for k in range(len(self.vid)):
            if uniform(seed, "root", self.vid[k]) >= some(c[k][m]):
                continue
            work = [([k], str(self.vid[k]), m)]
            while work:
                path, key, i = work.pop()
                v = path[-1]
                if how in ("descend", "printed"):
                    children = [j for j in sorted(self.after[v], key=lambda j: self.vid[j]) if c[j][i - 1] > 0]
                    rule = self._in_turn if how == "descend" else self._printed
                    taken, own = rule(children, v, i, c, p, seed, key, some)
                else:
                    children, sums, guide = self._line(v, i, m)
                    found, own, _, _ = next_hits(sums, p, seed, key, guide if how == "guide" else None)
                    taken = [children[x] for x in found]
                if own:
                    yield self.vid[path[0]], key, SEPARATOR.join(self.label[x] for x in path)
                work.extend(([*path, j], f"{key}-{self.vid[j]}", i - 1) for j in taken)

    def _line(self, v: int, i: int, m: int) -> tuple[list[int], list[int], list[int]]:
        """Children in order of id, their running sums with the path itself last, and the guide; made once for each vertex and level."""
        if (v, i, m) not in self._lines:
            c = self.counts(m)
            children = [j for j in sorted(self.after[v], key=lambda j: self.vid[j]) if c[j][i - 1] > 0]
            sums = [0, *accumulate([*(c[j][i - 1] for j in children), 1])]
            self._lines[v, i, m] = children, sums, guide_of(sums)
        return self._lines[v, i, m]

    def _in_turn(self, children, v, i, c, p, seed, key, some):
        left, taken = c[v][i], []
        for j in children:
            n = c[j][i - 1]
            chance = some(n) if taken else some(n) / some(left)
            if uniform(seed, "child", key, self.vid[j]) < chance:
                taken.append(j)
            left -= n
        return taken, not taken or uniform(seed, "self", key) < p

    def _printed(self, children, v, i, c, p, seed, key, some):
        """The rule as published, probabilities cut to at most 1; biased, kept for comparison."""
        rest = math.log1p(-p) if p < 1 else -math.inf
        skip = lambda n: min(1.0, math.exp(n * rest) / max(1e-300, -math.expm1(c[v][i] * rest)))
        taken = [j for j in children if uniform(seed, "child", key, self.vid[j]) > skip(c[j][i - 1])]
        return taken, not taken or uniform(seed, "self", key) < p


def guide_of(sums: list[int]) -> list[int]:
    """For equal cells of a line of items that end at ``sums[1:]``, the first item that can lie there."""
    n = 1 << max(0, (len(sums) - 2).bit_length())
    return [bisect.bisect_right(sums, sums[-1] * k // n) - 1 for k in range(n)]


def next_hits(sums: list[int], p: float, seed: int, key: str, guide: list[int] | None = None) -> tuple[list[int], bool, int, int]:
    """Sampled items among those that end at ``sums[1:]``, each of whose elements is drawn with p, given that some is; the last item, of
    one element, is the path itself. Returns the items, whether the last is among them, how many numbers were drawn and how many
    comparisons the searches took. From a uniform number follows how far the next drawn element lies; whose it is says a search by halving,
    or one from the guide's place on. The first number is drawn below the chance of any hit, so there is one."""
    rest = math.log1p(-p) if p < 1 else -math.inf
    end, at, found, turn, steps = sums[-1], 0, [], 0, 0
    while at < end:
        u = uniform(seed, "hit", key, turn)
        if turn == 0:
            u *= -math.expm1(end * rest)
        turn += 1
        far = at + (math.floor(math.log1p(-u) / rest) if p < 1 else 0)
        if far >= end:
            break
        if guide is not None:
            k = guide[far * len(guide) // end]
            steps += 1
            while sums[k + 1] <= far:
                k += 1
                steps += 1
        else:
            k, high = 0, len(sums) - 2
            while k < high:
                middle = (k + high) // 2
                steps += 1
                k, high = (middle + 1, high) if sums[middle + 1] <= far else (k, middle)
        if k == len(sums) - 2:
            return found, True, turn, steps
        found.append(k)
        at = sums[k + 1]
    return found, False, turn, steps


def hash_of(codes: list[int]) -> tuple[int, int]:
    out = []
    for base, prime in zip(BASES, PRIMES, strict=True):
        h = 0
        for code in codes:
            h = (h * base + code) % prime
        out.append(h)
    return out[0], out[1]


def ranks(count: int, p: float, seed: int, vid: int) -> list[int]:
    """Which of ``count`` numbered elements are drawn, each with p, given that some is: the first number is drawn below the chance of any."""
    rest = math.log1p(-p) if p < 1 else -math.inf
    out, at, turn = [], 0, 0
    while at < count:
        u = uniform(seed, "rank", vid, turn)
        if turn == 0:
            u *= -math.expm1(count * rest)
        at += math.floor(math.log1p(-u) / rest) if p < 1 else 0
        if at >= count:
            break
        out.append(at)
        at, turn = at + 1, turn + 1
    return out
