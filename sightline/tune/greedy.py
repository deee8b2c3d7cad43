"""Best configuration, the joint greedy tuner with its modules, the baselines' tuners, and the choice of a point."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from ..model.schemas import CELL, PROXY_SIZES, WIDTH
from .trial import Config, changed

GAPS = (1, 2, 4, 8, 16, 32)
Evaluate = Callable[[list[Config]], list[dict]]


def resolution_ladder(width: int = WIDTH, rungs: int = 6, factor: float = 0.85) -> list[int]:
    """Widths shrunk by 15 per cent a side."""
    return [round(width * factor**k) for k in range(rungs)]


def next_gap(gap: int, step: float = 0.3, rule: str = "goal") -> int | None:
    """The next power of two that is ``step`` faster; the literal rule multiplies by the step."""
    want = gap / (1 - step) if rule == "goal" else gap * step
    for g in GAPS:
        if g >= want and (g > gap or rule == "literal"):
            return g
    return None


def find_best(evaluate: Evaluate, start: Config | None = None) -> tuple[Config, list[dict]]:
    """The most accurate configuration, without a proxy and with the overlap tracker: down the resolutions until accuracy
    falls, then down the rates until it falls; ties go to the cheaper."""
    best = start or Config()
    trace: list[dict] = []
    now = evaluate([best])[0]
    trace.append(now | {"step": "start"})
    for step, options in (("resolution", [changed(best, width=w) for w in resolution_ladder()[1:]]), ("rate", None)):
        for option in options if options is not None else [changed(best, gap=g) for g in GAPS[1:]]:
            got = evaluate([option])[0]
            trace.append(got | {"step": step})
            if got["accuracy"] < now["accuracy"]:
                break
            best, now = option, got
    return best, trace


class DetectionModule:
    """Every architecture and resolution is tried once; proposes the most accurate one that is ``step`` faster."""

    name = "detection"

    def cache(self, evaluate: Evaluate, base: Config) -> None:
        options = [changed(base, arch=a, width=w) for a in ("one_stage", "two_stage") for w in resolution_ladder()]
        self.table = {(r["config"].arch, r["config"].width): (r["sec"], r["accuracy"]) for r in evaluate(options)}

    def propose(self, cfg: Config, step: float) -> Config | None:
        bound = (1 - step) * self.table[cfg.arch, cfg.width][0]
        fine = [(acc, -sec, k) for k, (sec, acc) in self.table.items() if sec <= bound + 1e-9]
        if not fine:
            return None
        arch, width = max(fine)[2]
        return changed(cfg, arch=arch, width=width)


class ProxyModule:
    """Every proxy size and threshold is tried once, on every frame; proposes the one of greatest recall that is ``step`` faster than now."""

    name = "proxy"

    def __init__(self, thresholds: Iterable[float] = (0.05, 0.2, 0.4, 0.6, 0.8)):
        self.thresholds = tuple(thresholds)

    def cache(self, evaluate: Evaluate, base: Config) -> None:
        options = [changed(base, gap=1, proxy=p, threshold=b) for p in range(len(PROXY_SIZES)) for b in self.thresholds]
        rows = evaluate([changed(base, gap=1), *options])
        self.table = {(r["config"].proxy, r["config"].threshold if r["config"].proxy is not None else None): (r["sec"], r["recall"]) for r in rows}

    def propose(self, cfg: Config, step: float) -> Config | None:
        now = self.table[cfg.proxy, cfg.threshold if cfg.proxy is not None else None][0]
        fine = [(recall, -sec, k) for k, (sec, recall) in self.table.items() if k[0] is not None and sec <= (1 - step) * now + 1e-9]
        if not fine:
            return None
        proxy, b = max(fine)[2]
        return changed(cfg, proxy=proxy, threshold=b)


class TrackingModule:
    name = "tracking"

    def cache(self, evaluate: Evaluate, base: Config) -> None:
        pass

    def propose(self, cfg: Config, step: float) -> Config | None:
        g = next_gap(cfg.gap, step)
        return changed(cfg, gap=g) if g else None


def tune(evaluate: Evaluate, start: Config, modules: list, step: float = 0.3, points: int = 8) -> tuple[list[dict], int]:
    """The speed-accuracy curve: each round every module proposes one configuration about ``step`` faster, all are tried in one job, and the
    most accurate is the next point (ties: the cheaper). Returns the curve and the number of trials."""
    for m in modules:
        m.cache(evaluate, start)
    curve = [evaluate([start])[0] | {"module": "start", "round": 0}]
    trials = 1
    for n in range(1, points):
        offers = {c.id: (c, m.name) for m in modules if (c := m.propose(curve[-1]["config"], step)) is not None}
        if not offers:
            break
        got = evaluate([c for c, _ in offers.values()])
        trials += len(got)
        best = max(got, key=lambda r: (round(r["accuracy"], 12), -r["sec"]))
        curve.append(best | {"module": offers[best["config"].id][1], "round": n})
    return curve, trials


def brute(evaluate: Evaluate, base: Config, widths: list[int], gaps: list[int], proxies: list[tuple[int | None, float]]) -> list[dict]:
    """All combinations of a small space."""
    return evaluate([changed(base, width=w, gap=g, proxy=p, threshold=b) for w in widths for g in gaps for p, b in proxies])


def rate_res(evaluate: Evaluate, start: Config, points: int = 8) -> list[dict]:
    """Baseline: detector resolution and sampling rate only, overlap tracker."""
    return tune(evaluate, changed(start, tracker="overlap", proxy=None, refine="none"), [DetectionModule(), TrackingModule()], points=points)[0]


def frame_gate(evaluate: Evaluate, start: Config, thresholds: Iterable[float] = (0.1, 0.3, 0.5, 0.7, 0.9)) -> list[dict]:
    """Baseline: a frame classifier decides whether the detector runs on a frame at all."""
    return evaluate([changed(start, tracker="overlap", gate=b) for b in thresholds])


def var_rate(evaluate: Evaluate, start: Config, tolerances: Iterable[float] = (0.1, 0.3, 0.5, 0.7)) -> list[dict]:
    """Baseline: variable gaps with two-frame matching under error tolerances, ends repaired with extra frames."""
    return evaluate([changed(start, tracker="overlap", gap=16, tolerance=b, refine="frames") for b in tolerances])


def pareto(rows: list[dict]) -> list[dict]:
    """Rows that no cheaper row reaches in accuracy."""
    out: list[dict] = []
    for r in sorted(rows, key=lambda r: (r["sec"], -r["accuracy"])):
        if not out or r["accuracy"] > out[-1]["accuracy"]:
            out.append(r)
    return out


def pick(curve: list[dict], within: float | None = 0.05, least: float | None = None) -> dict | None:
    """The fastest row within some accuracy points of the best, or of a least accuracy."""
    bound = least if least is not None else max(r["accuracy"] for r in curve) - within
    return min((r for r in curve if r["accuracy"] >= bound - 1e-12), key=lambda r: r["sec"], default=None)


assert CELL == 32
