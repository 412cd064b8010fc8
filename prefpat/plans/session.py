"""The preference loop: mine, interact, learn, repeat.

A round keeps the best of the previous ordered query, fills up from random cells
under the current weights, asks for an order, adds the ranking to the feedback, fits
the weights anew and uses them in the next round's sampling weight.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np

from prefpat.functions.features import FeatureSpec
from prefpat.functions.model import Weights
from prefpat.functions.rng import u01_py
from prefpat.operators.xorcells import CellBounds, draw_py, estimate_m
from prefpat.plans.learn import drawn_coordinates, scd_l1
from prefpat.plans.spaces import Shown
from prefpat.plans.users import Ranker

ATTEMPTS = 5


@dataclass(frozen=True)
class LoopConfig:
    k: int = 5
    l: int = 1  # noqa: E741
    A: float = 0.5
    features: str = "ILFT"
    cell: object = ("top", 1)
    lam: float = 1e-3
    T: int = 1000
    kappa: float = 0.9
    seed: int = 0
    active_only: bool = False
    warm_start: bool = False
    learn: bool = True
    transactions: str = "literal"

    @classmethod
    def recommended(cls) -> LoopConfig:
        return cls()

    def replace(self, **changes) -> LoopConfig:
        return replace(self, **changes)

    def __post_init__(self):
        if not 0 <= self.l < self.k:
            raise ValueError("fewer patterns are retained than shown")
        if not 0 < self.A <= 1:
            raise ValueError("the floor lies in (0, 1]")
        if self.transactions not in ("literal", "grouped"):
            raise ValueError("transactions are drawn literally or grouped")
        if self.active_only and FeatureSpec.of(self.features).has("transactions") and self.transactions == "literal":
            raise ValueError("which transactions are active is known to the grouped form only")


@dataclass
class Round:
    iter: int
    query: list[tuple[Shown, str]]  # with origin: retained, sampled or topped_up
    ordered: list[tuple[Shown, float]]
    pairs: int
    constraints: int


@dataclass
class PreferenceLoop:
    """One session over a space; ``step`` is a round, ``run`` several."""

    space: object
    cfg: LoopConfig
    rounds: list[Round] = field(default_factory=list)

    def __post_init__(self):
        self.weights = Weights.zero(self.space.n_items)
        self.bounds = CellBounds(self.cfg.kappa)
        self.spec = FeatureSpec.of(self.cfg.features)
        self.last_fit: np.ndarray | None = None

    # sampling

    def pick(self, cell: list[tuple[int, Shown]], w_max: float, first: int, last: int) -> list[Shown] | None:
        """The accepted cell's contribution, best or drawn first; None without one."""
        for m in range(first, last + 1):
            own = [s for met, s in cell if met >= m]
            weight = sum(s.w for s in own) / w_max
            if weight < self.bounds.low and last > 0:
                return None
            if weight <= self.bounds.high:
                return own
        return None

    def choose(self, own: list[Shown], salt: str) -> list[Shown]:
        if self.cfg.cell == "random":
            return [min(own, key=lambda s: (-math.log(u01_py(salt, s.pattern)) / s.w, s.pattern))] if own else []
        return sorted(own, key=lambda s: (-round(s.w, 9), s.pattern))[: self.cfg.cell[1]]

    def sample(self, need: int, without: set[str], salt: str) -> list[tuple[Shown, str]]:
        """New distinct patterns from random cells; if cells fail, the heaviest fill up."""
        if need <= 0:
            return []
        total, w_max = self.space.total_and_max(self.weights, self.cfg.A)
        first, last = self.constraints = estimate_m(total, w_max, self.bounds)
        each = 1 if self.cfg.cell == "random" else self.cfg.cell[1]
        found: list[tuple[Shown, str]] = []
        taken = set(without)
        for attempt in range(ATTEMPTS):
            if len(found) >= need:
                break
            draws = 2 * -(-(need - len(found)) // each)
            key = f"{self.cfg.seed}/{salt}/{attempt}"
            drawn = draw_py(last, self.space.n_items, range(draws), key)
            for d, cell in enumerate(self.space.cells(self.weights, self.cfg.A, drawn, first)):
                own = self.pick(cell, w_max, first, last)
                for s in self.choose(own, f"{key}/{d}") if own else []:
                    if s.pattern not in taken and len(found) < need:
                        taken.add(s.pattern)
                        found.append((s, "sampled"))
        if len(found) < need:
            spare = [s for s in self.space.heaviest(self.weights, self.cfg.A, need + len(taken)) if s.pattern not in taken]
            found += [(s, "topped_up") for s in spare[: need - len(found)]]
        return found

    # learning

    def all_shown(self) -> list[Shown]:
        shown = {s.pattern: s for r in self.rounds for s, _ in r.ordered}
        return [shown[p] for p in sorted(shown)]

    def plain_features(self, shown: list[Shown]) -> np.ndarray:
        """Items, length and frequency, as far as they take part."""
        blocks = [np.zeros((len(shown), 0))]
        if self.spec.has("items"):
            items = np.zeros((len(shown), self.space.n_items))
            for i, s in enumerate(shown):
                items[i, list(s.items)] = 1
            blocks.append(items)
        if self.spec.has("length"):
            blocks.append(np.array([[s.len / max(self.space.n_items, 1)] for s in shown]))
        if self.spec.has("frequency"):
            blocks.append(np.array([[s.sup / max(self.space.n, 1)] for s in shown]))
        return np.concatenate(blocks, axis=1)

    def deltas(self, shown: list[Shown], features: np.ndarray) -> np.ndarray:
        at = {s.pattern: i for i, s in enumerate(shown)}
        pairs = [(at[a.pattern], at[b.pattern]) for r in self.rounds for i, (a, x) in enumerate(r.ordered) for b, y in r.ordered[i + 1 :] if x != y]
        return np.array([features[a] - features[b] for a, b in pairs]).reshape(len(pairs), features.shape[1])

    def fit(self) -> None:
        """Weights from all rankings so far.

        With transactions as features an update may fall on any of them. Which ones the
        updates fall on is drawn first; only those, at most one for each update, are
        fetched, and only they can get a weight. ``grouped`` learns one weight for all
        transactions that hold the same shown patterns and shares it among them.
        """
        cfg, shown, seed = self.cfg, self.all_shown(), f"{self.cfg.seed}/{len(self.rounds)}"
        features = self.plain_features(shown)
        width = features.shape[1]
        if not self.spec.has("transactions"):
            start = self.last_fit if cfg.warm_start and self.last_fit is not None and len(self.last_fit) == width else None
            w = scd_l1(self.deltas(shown, features), cfg.lam, cfg.T, seed, start, cfg.active_only).weights
            self.last_fit, transactions = w, []
        elif cfg.transactions == "literal":
            drawn = drawn_coordinates(width + self.space.n, cfg.T, seed)
            numbers = sorted({j - width for j in drawn if j >= width})
            masks = self.space.transactions_at(numbers)
            own = np.array(masks, dtype=np.int64).reshape(len(masks), -1)
            inside = np.array([((own & np.array(s.masks)) == np.array(s.masks)).all(axis=1) for s in shown], dtype=float).reshape(len(shown), len(numbers))
            place = {n + width: i + width for i, n in enumerate(numbers)}
            w = scd_l1(self.deltas(shown, np.concatenate([features, inside], axis=1)), cfg.lam, cfg.T, order=[place.get(j, j) for j in drawn]).weights
            transactions = [(m, float(x)) for m, x in zip(masks, w[width:]) if x]
        else:
            inside, _, groups = self.space.coverage(shown)
            w = scd_l1(self.deltas(shown, np.concatenate([features, inside.astype(float)], axis=1)), cfg.lam, cfg.T, seed, None, cfg.active_only).weights
            weight = {g: float(x) for g, x in zip(groups, w[width:]) if x}
            members = self.space.members(shown, list(weight)) if weight else {}
            transactions = [(m, x / len(members[g])) for g, x in weight.items() for m in members[g]]
        self.weights = self.as_weights(w, transactions)

    def as_weights(self, w: np.ndarray, transactions: list) -> Weights:
        out, at = Weights.zero(self.space.n_items), 0
        if self.spec.has("items"):
            out.items, at = w[: self.space.n_items].copy(), self.space.n_items
        if self.spec.has("length"):
            out.length, at = float(w[at]), at + 1
        if self.spec.has("frequency"):
            out.frequency = float(w[at])
        out.transactions = transactions
        return out

    # the loop

    def compose(self) -> list[tuple[Shown, str]]:
        kept = [(s, "retained") for s, _ in self.rounds[-1].ordered[: self.cfg.l]] if self.rounds else []
        return kept + self.sample(self.cfg.k - len(kept), {s.pattern for s, _ in kept}, f"round{len(self.rounds) + 1}")

    def step(self, ranker: Ranker) -> Round:
        query = self.compose()
        ordered = ranker.order([s for s, _ in query])
        pairs = sum(x != y for i, (_, x) in enumerate(ordered) for _, y in ordered[i + 1 :])
        self.rounds.append(Round(len(self.rounds) + 1, query, ordered, pairs, self.constraints[1]))
        if self.cfg.learn:
            self.fit()
        return self.rounds[-1]

    def run(self, iters: int, ranker: Ranker) -> list[Round]:
        return [self.step(ranker) for _ in range(iters)]

    def current(self) -> list[Shown]:
        """What can be used now: the last query in the user's order."""
        return [s for s, _ in self.rounds[-1].ordered] if self.rounds else []

    def more(self, n: int) -> list[Shown]:
        """Further patterns under the current weights, unlike those shown last."""
        return [s for s, _ in self.sample(n, {s.pattern for s in self.current()}, f"more{len(self.rounds)}")]

    def rows(self, session_id: str) -> list[dict]:
        """Query rows in the user's order, for append-only logs."""
        out = []
        for r in self.rounds:
            origin = {s.pattern: o for s, o in r.query}
            out += [dict(session_id=session_id, iter=r.iter, pos=i + 1, pattern=s.pattern, level=float(v), origin=origin[s.pattern], w=s.w, phi=s.phi, pct=s.pct) for i, (s, v) in enumerate(r.ordered)]
        return out


ROW_SCHEMA = "session_id string, iter int, pos int, pattern string, level double, origin string, w double, phi double, pct double"
