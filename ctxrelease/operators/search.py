"""Sampling and searching contexts in memory, for one record and many trials.

A Search verifies masks against a slice and remembers verdicts, so that trials, budgets and methods share them.
Moves are arg max draws with noise keyed by (trial, step, mask), hence the same in the distributed versions.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from ctxrelease.functions.mechanism import NoNoise, NoValidContext, allocate, draw_local, draws_charged, weight
from ctxrelease.schema import ContextSchema

from .detectors import Detector, Slice


#: Random contexts tried for each wanted sample before the uniform sampler settles for fewer.
TRIALS_PER_SAMPLE = 400


#: Callers' utilities by name: a score of contexts' moments (n, s, ss, lo, hi, as arrays) and its stated sensitivity.
UTILITIES: dict[str, tuple[Callable[[dict], np.ndarray], float]] = {}


def register_utility(name: str, score: Callable[[dict], np.ndarray], sensitivity: float = 1.0) -> None:
    """Makes a utility known to releases. The sensitivity is the caller's word: the budget's meaning rests on it."""
    if name in ("population", "overlap") or not sensitivity > 0:
        raise ValueError("a utility needs a name of its own and a positive sensitivity")
    UTILITIES[name] = (score, sensitivity)


@dataclass
class Outcome:
    """One search: the context (public), and what only the owner may see."""

    ctx: int
    utility: float
    eps: float
    verified: int
    draws: int
    trials: int
    path: list[int] = field(default_factory=list)


class Search:
    def __init__(self, schema: ContextSchema, part: Slice, detector: Detector, cell: int, x: int, start: int | None = None, overlap: bool = False, utility: Callable[[dict], np.ndarray] | None = None, sensitivity: float = 1.0):
        """utility: a caller's score of contexts' moments (n, s, ss, lo, hi), with its stated sensitivity."""
        self.utility, self.sensitivity = utility, sensitivity
        self.schema, self.part, self.detector, self.cell, self.x = schema, part, detector, cell, x
        self.overlap, self.start = overlap, start
        self.free = schema.free_bits(cell)
        self.memo: dict[int, float | None] = {}  # utility, or None if not valid

    def utilities(self, masks: list[int]) -> list[float | None]:
        new = [c for c in dict.fromkeys(masks) if c not in self.memo]
        for at in range(0, len(new), 2048):
            ctxs = np.array(new[at : at + 2048], np.int64)
            flag, _ = self.detector.flags(self.part, ctxs, self.x)
            seen = ctxs & self.start if self.overlap else ctxs
            for c, ok, u in zip(ctxs.tolist(), flag.tolist(), self._scores(seen).tolist()):
                self.memo[c] = float(u) if ok else None
        return [self.memo[c] for c in masks]

    def valid_among(self, masks: list[int]) -> list[int]:
        """The valid ones, without remembering the others."""
        out: list[int] = []
        for at in range(0, len(masks), 2048):
            ctxs = np.array(masks[at : at + 2048], np.int64)
            out += ctxs[self.detector.flags(self.part, ctxs, self.x)[0]].tolist()
        return out

    def _scores(self, ctxs: np.ndarray) -> np.ndarray:
        stats = self.part.stats(ctxs)
        return stats["n"] if self.utility is None else self.utility(stats)

    def require_start(self) -> int:
        if self.start is None or self.utilities([self.start])[0] is None:
            raise NoValidContext("the search needs a context in which the record is an outlier")
        return self.start

    def all_candidates(self) -> list[int]:
        if len(self.free) > 22:
            raise ValueError(f"2^{len(self.free)} candidates: use a sampling method")
        out = np.array([self.cell], np.int64)
        for b in self.free:
            out = np.concatenate([out, out | b])
        return out.tolist()

    def valid(self) -> dict[int, float]:
        masks = self.all_candidates()
        return {c: u for c, u in zip(masks, self.utilities(masks)) if u is not None}

    # the methods; each returns the draw, its path and counters

    def direct(self, eps: float, noise, trial=0, convention: str = "eps1") -> Outcome:
        valid = self.valid()
        if not valid:
            raise NoValidContext("the record is an outlier in no context")
        masks = list(valid)
        e1 = allocate("direct", eps, 0)
        k = draw_local(masks, list(valid.values()), weight(e1, self.sensitivity, convention), noise, trial, 0)
        return Outcome(masks[k], valid[masks[k]], eps, 1 << len(self.free), 1, 0)

    def uniform(self, eps: float, n: int, noise, trial=0, p: float = 0.5, distinct: bool = True, max_trials: int | None = None, force_bits: bool = True, inclusive: bool = False, convention: str = "eps1") -> Outcome:
        """Independent random bits, kept if valid, until there are n; then one draw.

        Sampling ends after `max_trials` random contexts (TRIALS_PER_SAMPLE for each wanted one, if not given), with as
        many as were found: a record may have fewer valid contexts than n. Its counters are those of the sampling alone.
        """
        goal, got, seen, tried = n + inclusive, [], set(), 0
        max_trials = TRIALS_PER_SAMPLE * goal if max_trials is None else max_trials
        bits = self.free if force_bits else [1 << k for k in range(self.schema.t)]
        while len(got) < goal and tried < max_trials:
            batch = []
            for i in range(tried, min(tried + 64, max_trials)):
                mask = self.cell if force_bits else 0
                for j, b in enumerate(bits):
                    if noise.uniform(trial, "u", i, j) < p:
                        mask |= b
                batch.append(mask)
            for mask, u in zip(batch, self.utilities([c for c in batch])):
                tried += 1
                if u is None or mask & self.cell != self.cell or (distinct and mask in seen):
                    continue
                seen.add(mask)
                got.append(mask)
                if len(got) == goal:
                    break
        if not got:
            raise NoValidContext("no valid context among the trials")
        e1 = allocate("uniform", eps, n)
        k = draw_local(got, [self.memo[c] for c in got], weight(e1, self.sensitivity, convention), noise, trial, "final")
        return Outcome(got[k], self.memo[got[k]], eps, tried, 1, tried, got)

    def walk(self, eps: float, n: int, noise, trial=0, distinct: bool = False, inclusive: bool = False, convention: str = "eps1") -> Outcome:
        """Moves to a uniformly random valid neighbour; one draw over the path."""
        at = self.require_start()
        path, verified = [at], 0
        for step in range(1, n + inclusive):
            order = sorted((at ^ b for b in self.free), key=lambda c: (noise.uniform(trial, step, c), c))
            nxt = None
            for c, u in zip(order, self.utilities(order)):
                verified += 1
                if u is not None:
                    nxt = c
                    break
            if nxt is None:
                break
            at = nxt
            path.append(at)
        pool = list(dict.fromkeys(path)) if distinct else path
        e1 = allocate("walk", eps, n)
        k = draw_local(pool, [self.memo[c] for c in pool], weight(e1, self.sensitivity, convention), noise, trial, "final")
        return Outcome(pool[k], self.memo[pool[k]], eps, verified, 1, 0, path)

    def dfs(self, eps: float, n: int, noise, trial=0, final: str = "visited", inclusive: bool = False, convention: str = "eps1") -> Outcome:
        """A stack; each step draws among the unvisited valid neighbours of its top, or goes back."""
        at = self.require_start()
        factor = weight(allocate("dfs", eps, n, final, inclusive), self.sensitivity, convention)
        stack, visited, verified, draws = [at], [at], 0, 0
        while stack and len(visited) < n + inclusive:
            around = [c for b in self.free if (c := stack[-1] ^ b) not in visited]
            verified += len(around)
            kids = [(c, u) for c, u in zip(around, self.utilities(around)) if u is not None]
            if not kids:
                stack.pop()
                continue
            k = draw_local([c for c, _ in kids], [u for _, u in kids], factor, noise, trial, len(visited))
            draws += 1
            stack.append(kids[k][0])
            visited.append(kids[k][0])
        if final == "last":
            ctx = visited[-1]
        else:
            ctx = visited[draw_local(visited, [self.memo[c] for c in visited], factor, noise, trial, "final")]
            draws += 1
        return Outcome(ctx, self.memo[ctx], eps, verified, draws, 0, visited)

    def bfs(self, eps: float, n: int, noise, trial=0, inclusive: bool = False, convention: str = "eps1") -> Outcome:
        """A frontier; each step draws from all of it and adds the drawn one's unvisited valid neighbours."""
        at = self.require_start()
        factor = weight(allocate("bfs", eps, n, inclusive=inclusive), self.sensitivity, convention)
        frontier: dict[int, float] = {at: self.memo[at]}
        visited: list[int] = []
        verified = draws = 0
        while frontier and len(visited) < n + inclusive:
            masks = list(frontier)
            at = masks[draw_local(masks, list(frontier.values()), factor, noise, trial, len(visited))]
            draws += 1
            visited.append(at)
            del frontier[at]
            around = [c for b in self.free if (c := at ^ b) not in frontier and c not in visited]
            verified += len(around)
            frontier |= {c: u for c, u in zip(around, self.utilities(around)) if u is not None}
        ctx = visited[draw_local(visited, [self.memo[c] for c in visited], factor, noise, trial, "final")]
        return Outcome(ctx, self.memo[ctx], eps, verified, draws + 1, 0, visited)

    def greedy(self, n: int, kind: str = "bfs") -> Outcome:
        """The plain search that always takes the best: the limit of an unlimited budget; not private."""
        return getattr(self, kind)(1.0, n, NoNoise())

    def run(self, method: str, eps: float, n: int, noise, trial=0, **options) -> Outcome:
        if method == "direct":
            return self.direct(eps, noise, trial, **options)
        if method.startswith("greedy"):
            return self.greedy(n, method.partition("_")[2] or "bfs")
        return getattr(self, method)(eps, n, noise, trial, **options)


def starting_context(search: Search, strategy: str = "minimal", noise=None, max_trials: int = 200_000) -> int:
    """A valid context that depends on the data through the valid set only.

    `minimal`: fewest bits, then smallest mask; `uniform`: the first valid one of random candidates.
    """
    if strategy == "uniform":
        for i in range(max_trials):
            mask = search.cell
            for j, b in enumerate(search.free):
                if noise.uniform("start", i, j) < 0.5:
                    mask |= b
            if search.utilities([mask])[0] is not None:
                return mask
        raise NoValidContext("no valid context among the trials")
    if strategy != "minimal":
        raise ValueError(strategy)
    layer = [search.cell]
    for _ in range(len(search.free) + 1):
        found = [c for at in range(0, len(layer), 65_536) for c in search.valid_among(layer[at : at + 65_536])]
        if found:
            return min(found)
        # a mask's set bits above its highest chosen one: every larger mask is made once, and in pieces when verified
        layer = [c | b for c in layer for b in search.free if b > ((c ^ search.cell).bit_length() and 1 << ((c ^ search.cell).bit_length() - 1))]
    raise NoValidContext("the record is an outlier in no context")


__all__ = ["Outcome", "Search", "starting_context", "draws_charged"]
