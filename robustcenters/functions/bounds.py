"""Closed forms: sizes, memory, parameter caps and the constants of the guarantees, as plain driver arithmetic."""

from __future__ import annotations

import math

DIRECT_CAP = math.sqrt(3 / 8) - 0.5
REFINED_CAP = (math.sqrt(3) - math.sqrt(2)) / 6
LOCAL_SEARCH_RATIO = 274
#: Seedings of which an approximation ratio is proven on every run; for the others beta is an assumption.
SEEDING_RATIO = {"exact": 1.0}


def kprime(k: int, z: int, center_factor: float = 1.0, outlier_factor: float = 1.0) -> int:
    if k < 1 or z < 0 or center_factor < 1 or outlier_factor < 1:
        raise ValueError("need k >= 1, z >= 0 and factors of at least 1")
    return math.ceil(center_factor * k) + math.ceil(outlier_factor * z)


def delta(gamma: float, beta: float, power: int = 2) -> float:
    """Precision of every cover."""
    return gamma / math.sqrt(2 * beta) if power == 2 else gamma / (2 * beta)


def check_gamma(gamma: float, variant: str, strict: bool = True, power: int = 2) -> bool:
    """Whether the guarantees hold at this precision; strict raises instead."""
    if not 0 < gamma < 1:
        raise ValueError("gamma must lie in (0, 1)")
    cap = 1.0 if power == 1 else DIRECT_CAP if variant in ("direct", "one_round") else REFINED_CAP
    if gamma <= cap:
        return True
    if strict:
        raise ValueError(f"gamma {gamma} is over the certified cap {cap:.6f} of the {variant} variant")
    return False


def partitions(n: int, k_prime: int, variant: str, max_rows: int | None = None) -> int:
    """Number of parts that balances a part against what it receives; never so few that a part exceeds max_rows."""
    rule = (n / max(1, k_prime)) ** (1 / 3 if variant == "direct" else 1 / 2)
    return max(1, round(rule), -(-n // max_rows) if max_rows else 1)


def coreset_quality(gamma: float, variant: str, power: int = 2) -> float:
    if power == 1:
        return gamma + gamma**2 if variant == "direct" else gamma + 2 * gamma**2 + gamma**3
    return 4 * gamma + 4 * gamma**2 if variant == "direct" else 11 * gamma**2 + 2 * math.sqrt(11) * gamma


def centroid_slack(gamma: float, variant: str, power: int = 2) -> float:
    if power == 1:
        return 1.5 * gamma + gamma**2 if variant == "direct" else 1.5 * gamma + 2 * gamma**2 + gamma**3
    return (27 if variant == "direct" else 47) * gamma


def distortion_factor(gamma: float, which: str) -> float:
    """Squared proxy distortion over OPT_k': first cover and direct coreset, compacted reference, refined coreset."""
    return {"first": 4, "direct": 4, "compact": 18, "refined": 11}[which] * gamma**2


def quality_from_distortion(d: float) -> float:
    return d + 2 * math.sqrt(d)


def end_to_end(gamma: float, variant: str, alpha: float = 1.0) -> float:
    """Explicit constant of alpha + O(gamma)."""
    s = coreset_quality(gamma, variant)
    return alpha * (1 + s) / (1 - s) * (1 + centroid_slack(gamma, variant))


def sizes(n: int, k_prime: int, gamma: float, beta: float, dimension: float, parts: int) -> dict[str, float]:
    """Shapes of the size bounds without their hidden constants."""
    b, log = (8 * math.sqrt(2 * beta) / gamma) ** dimension, math.log(max(n, 2))
    return {"first": parts * k_prime * b * log, "direct": parts**2 * k_prime * b**2 * log**2, "compact": k_prime * b * log, "refined": parts * k_prime * b**2 * log**2}


def memory(n: int, k_prime: int, gamma: float, beta: float, dimension: float, variant: str) -> float:
    b, log = (8 * math.sqrt(2 * beta) / gamma) ** (2 * dimension), math.log(max(n, 2)) ** 2
    return (n ** (2 / 3) * k_prime ** (1 / 3) if variant == "direct" else math.sqrt(n * k_prime)) * b * log


def constants_hold(grid: list[float] | None = None) -> list[tuple[str, bool]]:
    """The numeric facts that the guarantees rest on, checked on a grid of precisions up to the direct cap."""
    grid = [DIRECT_CAP * i / 1000 for i in range(1, 1001)] if grid is None else grid
    s = lambda g: 4 * g + 4 * g * g
    step = lambda g: (1 + 2 * s(g)) * ((1 + g) * (1 + s(g)) + (1 + 1 / g) * (g * g / 2) * (5 + s(g)))
    return [
        ("direct cap makes the coreset error one half", abs(s(DIRECT_CAP) - 0.5) < 1e-12),
        ("refined cap makes the compact error one half", abs(quality_from_distortion(18 * REFINED_CAP**2) - 0.5) < 1e-12),
        ("centroid step stays under 1 + 27 gamma", all(step(g) <= 1 + 27 * g for g in grid)),
        ("refined distortion is under 11 gamma squared", all(2 * g * g + 9 * g**4 <= 11 * g * g for g in grid if g <= REFINED_CAP)),
    ]
