"""Closed-form costs of the methods, with natural logarithms. Constants and o(1)
exponents that the analysis leaves open are 1 and 0: the values show the shape
of growth, not counts."""

from __future__ import annotations

import math


def ln(x: float) -> float:
    return math.log(x)


def cut_off(n: int, c: float) -> int:
    """The greatest whole length below log n to the base 1/sqrt(c)."""
    return math.floor(ln(n) / ln(1 / math.sqrt(c)) + 1e-9)


def walks_per_node(n: int, eps: float, scope: str = "per_node", delta: float | None = None) -> float:
    """Hoeffding's sample size with the error that truncation and rounding leave."""
    if eps <= 3 / n:
        raise ValueError(f"eps must be over 3/n = {3 / n:.4g}")
    fail = delta if delta is not None else {"per_node": 1 / n, "all_nodes": 1 / n**2}[scope]
    return ln(2 / fail) / (2 * (eps - 3 / n) ** 2)


def warm_up_walks(n: int, eps: float) -> float:
    return ln(2 * n * n) / (2 * eps * eps)


def warm_up_length(n: int, eps: float, c: float) -> float:
    """Longer walks have a probability of (eps/n)**3 at most."""
    return 3 * ln(n / eps) / ln(1 / math.sqrt(c))


def half_width(samples: int, delta: float) -> float:
    return math.sqrt(ln(2 / delta) / (2 * samples))


def min_alpha(n: int, c: float) -> float | None:
    """The least exponent of space that the condition n**alpha > ln(n)**5 / ln(1/sqrt(c)) allows;
    None if it is not below 1."""
    need = ln(n) ** 5 / ln(1 / math.sqrt(c))
    alpha = ln(need) / ln(n) if n > 1 else math.inf
    return alpha if alpha < 1 else None


def slice_exponent(n: int, alpha: float, c: float) -> float:
    """beta with n**beta = n**alpha / L: the space each of L lengths gets of a machine's."""
    return alpha - ln(max(1, cut_off(n, c))) / ln(n)


def alpha_for_constant(constant: float, n: int, alpha: float) -> float:
    """A smaller exponent whose space stays within n**alpha after growing by a constant factor."""
    return alpha - ln(constant) / ln(n)


def machines(n: int, m: int, alpha: float, log_power: int = 1) -> int:
    return math.ceil((m + n) / n**alpha * ln(n) ** log_power)


def owner(node: int, n: int, count: int) -> int:
    """Which of ``count`` machines (from 1) owns node 1..n."""
    return -(-node * count // n)


def _fixed(n, m, eps, c, **_):
    slack = eps - 3 / n
    space = m * ln(n) + n * ln(n) ** 4.5 + n * ln(n) ** 3 / (2 * slack**2)
    return ln(max(math.e, ln(n))) ** 2, space, eps


def _warm_up(n, m, eps, c, **_):
    return ln(n / eps), n * ln(n) * ln(n / eps) / eps**2, eps


def _jacobi(n, m, eps, c, l=10, b=100, iterations=5, **_):
    return n * l * (iterations + l) / b, b * l * l * ln(n) / eps**2 + n + m, None


def _unidirectional(n, m, eps, c, l=10, **_):
    return l, n * n * l * ln(n) / eps**2, eps


def _forest(n, m, eps, c, terms=10, **_):
    return ln(n) ** 2 / eps**2 + terms, m * ln(n) + terms * n, c * (1 - c**terms) * eps / (1 - c) + c ** (terms + 1)


#: rounds, total space a round and error (None: no guarantee) of each method.
METHODS = {"fixed_length": _fixed, "warm_up": _warm_up, "linear_jacobi": _jacobi, "unidirectional": _unidirectional, "linear_forest": _forest}


def space_per_machine(method: str, n: int, m: int, eps: float, c: float, machines_used: int = 10, alpha: float = 0.9, **options) -> float:
    total = METHODS[method](n, m, eps, c, **options)[1]
    if method == "fixed_length":
        return n**alpha
    if method == "linear_jacobi":
        return total - (n + m) + (n + m) / machines_used
    return total / machines_used if method == "linear_forest" else total


def sampler(n: int, m: int, walks: float, length: float) -> tuple[float, float]:
    """Rounds and total space of the sampler of ``walks`` walks of one length from every node."""
    rounds = ln(max(math.e, ln(n))) ** 2 + ln(max(math.e, length)) ** 2
    return rounds, m + n * length**3.5 + walks * n * length**2


def messages(n: int, eps: float, count: int = 1) -> float:
    """Walk-meet messages a machine."""
    return n * ln(n) ** 2 / (count * (eps - 3 / n) ** 2)
