"""Mining depths, frequency bounds and error bounds: pure formulas.

`delta` bounds how much any pattern's frequency changes between adjacent batches, `m` is the number
of batches of a window, `v` the number of batches in which a persistent pattern is in the top k.
"""

from __future__ import annotations

import math


def _check(m: int, delta: float, v: float | None = None) -> None:
    if m < 1 or delta < 0:
        raise ValueError("m starts at 1 and delta at 0")
    if v is not None and not 1 <= v <= m:
        raise ValueError(f"v lies between 1 and m = {m}, not {v}")


def slack_lookahead(delta: float) -> float:
    """Depth that holds the next batch's top k."""
    _check(1, delta)
    return 2 * delta


def slack_exact(m: int, delta: float) -> float:
    """Depth that every member of the window's top k reaches in every batch."""
    _check(m, delta)
    return 2 * (m - 1) * delta


def slack_persistent(m: int, v: float, delta: float) -> float:
    """Depth that every pattern in the top k of v batches reaches in the others."""
    _check(m, delta, v)
    return 2 * (m - v) * delta


def slack_heuristic(m: int, v: float, delta: float) -> float:
    """A deeper slack: m (1 - x)(2 + x) delta with x = v / m."""
    _check(m, delta, v)
    x = v / m
    return m * (1 - x) * (2 + x) * delta


def slack(name: str, m: int, v: float | None, delta: float) -> float:
    if name in ("batch_union", "sticky_union"):
        return 0.0
    if name == "lookahead":
        return slack_lookahead(delta)
    if name == "exact_depth":
        return slack_exact(m, delta)
    if name == "persistent_depth":
        return slack_persistent(m, v, delta)
    if name == "heuristic_depth":
        return slack_heuristic(m, v, delta)
    raise ValueError(f"{name} has no slack")


def frequency_floor(fk: float, theta: float) -> int:
    """Smallest whole frequency that is at least fk - theta, never below 1."""
    return max(1, math.ceil(fk - theta - 1e-9))


def bound_lower(sum_fk: float, m: int, v: float, delta: float) -> float:
    """Least window frequency of a pattern in the top k of v batches."""
    _check(m, delta, v)
    return sum_fk - (m - v) * (m - v + 1) * delta


def bound_upper(sum_fk: float, m: int, v: float, delta: float, form: str = "printed") -> float:
    """Window frequency that no pattern in the top k of fewer than v batches exceeds; 'tight' is the sharper sum."""
    _check(m, delta, v)
    if form not in ("printed", "tight"):
        raise ValueError("form is 'printed' or 'tight'")
    return sum_fk + v * (v + 1 if form == "printed" else v - 1) * delta


def phi_condition(m: int, v: float) -> float:
    """Value that phi / 2 has to exceed for the band gap to hold all that can mix in."""
    _check(m, 0, v)
    return max(1.0, (1 - v / m) * (m - v + 1))


def phi_ok(phi: float, m: int, v: float) -> bool:
    return phi / 2 > phi_condition(m, v)


def mu(m: int, v: float, phi: float) -> float:
    _check(m, 0, v)
    return min(m - v + 1, phi / 2, (math.sqrt(1 + 2 * m * phi) - 1) / 2)


def error_bound(eps: float, k: int, m: int, v: float, phi: float) -> float:
    """Most false positives or negatives of the persistent answer under (phi, eps)-separation."""
    return eps * k * m / mu(m, v, phi)


def error_bound_special(case: str, eps: float, k: int, m: int) -> float:
    """The three closed cases: v = 1, v = m, v = (m + 1) // 2."""
    if case == "one":
        return eps * k * m / (m - 1)
    if case == "all":
        return eps * k * m
    if case == "half":
        return 4 * eps * k * m**2 / (m**2 - 1)
    raise ValueError("case is 'one', 'all' or 'half'")
