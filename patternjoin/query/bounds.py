"""Upper bound on a join's output from a fractional edge cover."""

from __future__ import annotations

import math

from .model import JoinQuery


def cover_bound(q: JoinQuery, sizes: dict[str, int] | list[int]) -> tuple[float, list[float]]:
    """(bound, weight of each atom): minimise sum x_e log |R_e| with every variable covered.

    Solved as its dual (spread as much as possible over the variables, no atom above log |R|)
    by the simplex method with the smallest-index rule; the weights are the dual prices.
    """
    n = [sizes[a.rel] if isinstance(sizes, dict) else sizes[i] for i, a in enumerate(q.atoms)]
    if 0 in n:
        return 0.0, [1.0] * len(n)
    variables, m = q.variables, len(n)
    k = len(variables)
    rows = [[1.0 if v in a.vars else 0.0 for v in variables] + [1.0 if i == j else 0.0 for j in range(m)] + [math.log(n[i])]
            for i, a in enumerate(q.atoms)]
    price = [-1.0] * k + [0.0] * (m + 1)
    basis = list(range(k, k + m))
    while (c := next((j for j in range(k + m) if price[j] < -1e-12), None)) is not None:
        r = min((i for i in range(m) if rows[i][c] > 1e-12), key=lambda i: (rows[i][-1] / rows[i][c], basis[i]))
        pivot = rows[r][c]
        rows[r] = [x / pivot for x in rows[r]]
        for i in range(m):
            if i != r and rows[i][c]:
                f = rows[i][c]
                rows[i] = [x - f * y for x, y in zip(rows[i], rows[r], strict=True)]
        f = price[c]
        price = [x - f * y for x, y in zip(price, rows[r], strict=True)]
        basis[r] = c
    return math.exp(price[-1]), [round(x, 9) for x in price[k:k + m]]
