"""Budgets and methods: from what is wanted to gamma and a plan."""

from __future__ import annotations

import math
from dataclasses import dataclass

#: Constant of the spectral budget, read off measured errors (0.22 to 0.70); an observation, not a bound.
C1 = 0.7
GOALS = ("spectral", "similar")
METHODS = ("exact", "pair", "staged", "thinned")


def gamma_for_spectral(n: int, eps: float, c1: float = C1) -> float:
    """Budget for a relative spectral error of eps with probability one half: 4 c1^2 n / eps^2."""
    if n < 1 or not eps > 0:
        raise ValueError("n must be at least 1 and eps positive")
    return 4 * c1 * c1 * n / (eps * eps)


def gamma_for_similarity(s: float, alpha: float, method: str = "pair", h: float = 1.0) -> float:
    """Budget for pairs of cosine s or more, entries in [0, 1]: alpha / s.

    The staged and thinned methods cap each norm on its own, so on a pair of one small
    and one large norm they act with less than gamma. With entries of h or more, a
    cosine of s needs a smaller norm of at least s h times the larger, so no pair that
    qualifies gets less than s h gamma: their budget is raised by that factor.
    """
    if not 0 < s <= 1 or not alpha > 0 or not 0 < h <= 1:
        raise ValueError("s and h must be in (0, 1] and alpha positive")
    return alpha / s if method in ("pair", "exact") else alpha / (s * s * h)


def over_tail(alpha: float, delta: float) -> float:
    """Bound on the chance that an estimate exceeds 1 + delta times its true value."""
    return math.exp(alpha * (delta - (1 + delta) * math.log1p(delta)))


def under_tail(alpha: float, delta: float) -> float:
    """Bound on the chance that an estimate is below 1 - delta times its true value."""
    return math.exp(-alpha * delta * delta / 2)


def alpha_for(delta: float, fail: float, n_pairs: int) -> float:
    """Smallest alpha with which all pairs are within both tails at once, but for a chance of ``fail``: each tail gets fail / (2 n_pairs)."""
    if not delta > 0 or not 0 < fail < 1 or n_pairs < 1:
        raise ValueError("delta > 0, 0 < fail < 1, n_pairs >= 1")
    need = math.log(2.0 * n_pairs / fail)
    return max(need / ((1 + delta) * math.log1p(delta) - delta), 2 * need / (delta * delta))


def alpha_log_n(n: int) -> float:
    """The preset log n: cheap, with weak tails (0.61 and 0.56 at n = 100, delta = 0.5)."""
    return math.log(max(2, n))


def effective_gamma(gamma: float, norm_i: float, norm_j: float, method: str) -> float:
    """Budget that really acts on a pair: the staged and thinned methods cap each norm on its own."""
    if method in ("pair", "exact"):
        return min(gamma, norm_i * norm_j)
    root = math.sqrt(gamma)
    return min(root, norm_i) * min(root, norm_j)


def shuffle_bound(n: int, row_max: int, gamma: float, h: float = 1.0) -> float:
    """Bound on expected emissions: n L gamma / H^2."""
    return n * row_max * gamma / (h * h)


def key_bound(gamma: float, h: float = 1.0) -> float:
    """Bound on expected values of one key: gamma / H^2."""
    return gamma / (h * h)


def lower_bound(n: int, row_max: int) -> float:
    """Pairs that any algorithm must output on n/L groups of L equal columns: n (L - 1) / 2."""
    return n * (row_max - 1) / 2


@dataclass(frozen=True)
class SamplePlan:
    """What will run: gamma (for the matrix as it is, not scaled), method and what is promised."""

    goal: str
    method: str
    gamma: float
    seed: int = 7
    guarantee: str = ""
    target: float = 0.0

    def __post_init__(self) -> None:
        if self.goal not in GOALS or self.method not in METHODS:
            raise ValueError(f"goal is one of {GOALS}, method one of {METHODS}")


def plan(
    profile: dict, goal: str, eps: float | None = None, s: float | None = None, delta: float = 0.5, fail: float = 0.1, method: str | None = None,
    allow_heuristic: bool = False, expected: float | None = None, c1: float = C1, seed: int = 7, alpha: float | str | None = None,
) -> SamplePlan:
    """A plan for a matrix of the given profile (a row of operators.matrix.profile as a dict).

    Budgets are stated for entries scaled into [-1, 1]; dividing all entries by the
    largest magnitude is the same as multiplying gamma by its square, which is what
    the plan does. The spectral promise needs independent draws, so staged and thinned
    plans are refused for it unless allow_heuristic. The promise for similar pairs
    needs entries that aren't negative. alpha="log_n" takes the cheap preset, whose
    tails the promise then states. If sampling is expected to emit as much as all
    products, or the bound says it cannot pay, the plan is exact; ``expected``
    (cost.expected_emissions on a sample of rows) takes the place of the loose bound.
    """
    n, chosen = int(profile["n"]), method or "pair"
    scale, h = float(profile["most"] or 1.0) ** 2, float(profile["h"] or 1.0)
    if goal == "spectral":
        if eps is None:
            raise ValueError("the spectral goal needs eps")
        gamma = gamma_for_spectral(max(1, n), eps, c1)
        if chosen in ("staged", "thinned") and not allow_heuristic:
            raise ValueError(f"the {chosen} method's draws aren't independent: no spectral guarantee")
        promise = f"relative spectral error {eps} of the largest eigenvalue with probability 1/2, if the constant {c1} holds" if chosen == "pair" else "none (heuristic)"
    elif goal == "similar":
        if s is None:
            raise ValueError("the similar goal needs s")
        negative = (profile.get("smallest") or 0) < 0
        if negative and not allow_heuristic:
            raise ValueError("negative entries: no guarantee for single pairs")
        pairs = max(1, n * (n - 1) // 2)
        wanted = alpha_log_n(n) if alpha == "log_n" else alpha_for(delta, fail, pairs) if alpha is None else float(alpha)
        gamma = gamma_for_similarity(s, wanted, chosen, h)
        if alpha is None:
            promise = f"pairs of cosine {s} or more within a factor 1 +- {delta}, all at once with probability {1 - fail}"
        else:
            promise = f"a pair of cosine {s} or more is over 1 + {delta} times its value with probability {over_tail(wanted, delta):.3g} at most, under 1 - {delta} with {under_tail(wanted, delta):.3g}"
        promise = "none (negative entries)" if negative else promise
    else:
        raise ValueError(f"goal is one of {GOALS}")
    target = float(eps if goal == "spectral" else s)
    likely = expected if expected is not None else shuffle_bound(n, int(profile["row_max"]), gamma, h)
    if method is None and likely >= (profile["pairs"] or 0):
        return SamplePlan(goal, "exact", math.inf, seed, "exact", target)
    return SamplePlan(goal, chosen, gamma * scale, seed, promise, target)


def execute(matrix, the_plan: SamplePlan, norms=None, draw: str = "xxhash64"):
    """(i, j, cos, n_kept) by the plan."""
    from tallgram.operators.sampling import estimate

    method = "pair" if the_plan.method == "exact" else the_plan.method
    return estimate(matrix, method, the_plan.gamma, the_plan.seed, norms, draw)


#: Rows that the planner's estimate of emissions reads, by a hash of their ids.
PLAN_ROWS = 200_000


def plan_for(matrix, norms, goal: str, **wanted) -> SamplePlan:
    """The plan of a matrix: its profile, then expected emissions on a sample of rows (over PLAN_ROWS rows), then the choice."""
    from tallgram.operators.cost import expected_emissions
    from tallgram.operators.matrix import profile

    found = profile(matrix).first().asDict()
    if not found["pairs"]:
        return SamplePlan(goal, "exact", math.inf, wanted.get("seed", 7), "exact", float(wanted.get("eps") or wanted.get("s") or 0))
    sampled = plan(found, goal, expected=0.0, **wanted)
    if wanted.get("method") is not None:
        return sampled  # the choice is made, so no estimate of emissions is needed
    share = min(1.0, PLAN_ROWS / max(1, found["m"]))
    kind = "pair" if sampled.method in ("pair", "exact") else sampled.method
    likely = expected_emissions(matrix, sampled.gamma, norms, kind, share).first()["expected"]
    return plan(found, goal, expected=likely, **wanted)


def planned_pairs(matrix, s: float, draw: str = "xxhash64", **wanted):
    """(plan, pairs): from a matrix to (i, j, cos) of the pairs whose estimate is at least s (1 - delta), exact ones at least s."""
    from pyspark.sql import functions as F

    from tallgram.operators.norms import column_norms

    norms = column_norms(matrix)
    the_plan = plan_for(matrix, norms, "similar", s=s, **wanted)
    cut = s if the_plan.method == "exact" else s * (1 - wanted.get("delta", 0.5))
    return the_plan, execute(matrix, the_plan, norms, draw).where(F.col("cos") >= cut).select("i", "j", "cos")


def planned_gram(matrix, eps: float, draw: str = "xxhash64", **wanted):
    """(plan, upper triangle of the Gram matrix): estimated by the plan, the diagonal exact."""
    from tallgram.operators.gram import gram_from_cosines
    from tallgram.operators.norms import column_norms

    norms = column_norms(matrix)
    the_plan = plan_for(matrix, norms, "spectral", eps=eps, **wanted)
    return the_plan, gram_from_cosines(execute(matrix, the_plan, norms, draw).select("i", "j", "cos"), norms)


def planned_spectrum(matrix, n: int, eps: float, k: int | None = None, draw: str = "xxhash64", **wanted):
    """(plan, singular values, right vectors) of a matrix of n columns."""
    from tallgram.operators.spectral import spectral_factors

    the_plan, upper = planned_gram(matrix, eps, draw, **wanted)
    return the_plan, *spectral_factors(upper, n, k)
