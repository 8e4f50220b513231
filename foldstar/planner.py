"""When to factor: thresholds on tuple and feature ratios, and how they are tuned and judged."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from foldstar.normalized import Coo, FactoredMatrix

TUPLE_RATIO = 5.0
FEATURE_RATIO = 1.0


def should_factor(tuple_ratio: float, feature_ratio: float, tau: float = TUPLE_RATIO, rho: float = FEATURE_RATIO) -> bool:
    return tuple_ratio >= tau and feature_ratio >= rho


def should_factor_pairs(pairs: int, inputs: int, tau: float = TUPLE_RATIO) -> bool:
    """Many-to-many joins: rows of T over rows of the inputs takes the tuple ratio's place."""
    return pairs >= tau * max(inputs, 1)


def plan_star(t: FactoredMatrix, tau: float = TUPLE_RATIO, rho: float = FEATURE_RATIO) -> tuple[FactoredMatrix, list[bool]]:
    """Attribute tables that fail the rule are folded into the entity's own features; the rest stay links."""
    stats, verdicts = t.stats(), []
    rows, own, links = t.rows, list(t.own), []
    for link, s in zip(t.links, stats["links"]):
        go = should_factor(s["tuple_ratio"], s["feature_ratio"], tau, rho)
        verdicts.append(go)
        if go:
            links.append(link)
        else:
            block = link.block.wide() if isinstance(link.block, Coo) else link.block
            rows = block.joined(rows, link.column)
            own += block.names
    return FactoredMatrix(rows, own, links, [*t.trace, "plan"]), verdicts


@dataclass(frozen=True)
class Run:
    tuple_ratio: float
    feature_ratio: float
    seconds_m: float
    seconds_f: float

    @property
    def gain(self) -> float:
        return self.seconds_m / self.seconds_f


def tune_rule(runs: list[Run]) -> tuple[float, float]:
    """Smallest thresholds, tuple ratio first, under which no run that the rule factors was slower factored."""
    taus = sorted({0.0, *(r.tuple_ratio for r in runs)})
    rhos = sorted({0.0, *(r.feature_ratio for r in runs)})
    ok = [(t, f) for t in taus for f in rhos if all(r.gain >= 1 for r in runs if should_factor(r.tuple_ratio, r.feature_ratio, t, f))]
    covered = lambda p: sum(should_factor(r.tuple_ratio, r.feature_ratio, *p) for r in runs)
    return max(ok, key=lambda p: (covered(p), -p[0], -p[1]), default=(float("inf"), float("inf")))


def judge_rule(runs: list[Run], tau: float = TUPLE_RATIO, rho: float = FEATURE_RATIO) -> dict:
    """Right and wrong verdicts, and the largest gain that a wrong "stop" gave away."""
    out = {"go_right": 0, "go_wrong": 0, "stop_right": 0, "stop_wrong": 0, "gain_lost": 0.0}
    for r in runs:
        go, better = should_factor(r.tuple_ratio, r.feature_ratio, tau, rho), r.gain >= 1
        out[f"{'go' if go else 'stop'}_{'right' if go == better else 'wrong'}"] += 1
        if not go and better:
            out["gain_lost"] = max(out["gain_lost"], 1 - 1 / r.gain)
    return out


def uniqueness(df, column: str) -> float:
    """Distinct join values over rows."""
    r = df.agg(F.count("*").alias("n"), F.count_distinct(column).alias("u")).first()
    return r["u"] / r["n"] if r["n"] else 0.0
