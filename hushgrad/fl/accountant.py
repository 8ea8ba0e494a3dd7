"""Privacy actually spent, by Renyi composition of Gaussian rounds.

Independent of the noise formula's unknown constant.  One round releases a mean
whose replace-one sensitivity is `sensitivity`; without amplification T rounds
compose to order-a Renyi divergence a*T*s^2/(2*sigma^2), turned into (eps, delta)
at the best order.  Sampling is without replacement and adjacency replaces one
record, for which the standard subsampled bound differs, so no amplification is
claimed and the figure is an upper bound.  Searching stepsizes is not charged.
"""

from __future__ import annotations

import math

from hushgrad.fl.theory import Constants

ORDERS = [1 + x / 100 for x in range(1, 400)] + [5 + x / 4 for x in range(240)] + list(range(65, 512, 8))


def sensitivity(k: Constants, m: int, b: int) -> float:
    """Largest change of a round's local estimate when one record is replaced."""
    return 2 * (k.ga / b + k.gb / m)


def spent(sigma: float, rounds: int, sens: float, delta: float) -> float:
    """eps spent at delta by `rounds` releases with noise of standard deviation sigma."""
    if sigma == 0:
        return math.inf
    rho = rounds * sens * sens / (2 * sigma * sigma)
    return min(a * rho + math.log(1 / delta) / (a - 1) for a in ORDERS)
