"""How many draws each stratum gets. All inputs are one number for each stratum, held by the driver."""

from __future__ import annotations

from collections.abc import Hashable
from math import sqrt

Numbers = dict[Hashable, float]


def share_out(weights: Numbers, capacity: dict, n: int, floor: int = 0) -> dict:
    """n whole draws: the floor for each, the rest by weight and largest remainder (ties by stratum), never over capacity.

    What a full stratum cannot take is shared again; if all open weights are zero, by open capacity.
    """
    ids = sorted(capacity)
    n = min(int(n), int(sum(capacity.values())))
    got = dict.fromkeys(ids, 0)
    by_weight = sorted(ids, key=lambda h: (-weights.get(h, 0), ids.index(h)))
    for h in by_weight:
        got[h] = min(floor, capacity[h], n - sum(got.values()))
    while (rest := n - sum(got.values())) > 0:
        room = {h: capacity[h] - got[h] for h in ids if capacity[h] > got[h]}
        open_weights = {h: weights.get(h, 0) for h in room}
        if sum(open_weights.values()) <= 0:
            open_weights = dict(room)
        total = sum(open_weights.values())
        exact = {h: rest * w / total for h, w in open_weights.items()}
        want = {h: int(x + 1e-9) for h, x in exact.items()}
        extra = rest - sum(want.values())
        order = sorted(exact, key=lambda h: (-round(exact[h] - want[h], 9), ids.index(h)))
        for h in [h for h in order if open_weights[h] > 0][:extra]:
            want[h] += 1
        for h in room:
            got[h] += min(room[h], want[h])
    return got


def proportional(sizes: dict, n: int, left: dict | None = None, floor: int | None = None) -> dict:
    """By size; each stratum with rows gets one if there are enough draws."""
    left = left or sizes
    floor = (1 if n >= len(sizes) else 0) if floor is None else floor
    return share_out(sizes, left, n, floor)


def neyman(sizes: dict, heterogeneity: Numbers, n: int, left: dict, floor: int = 1) -> dict:
    """By size times the root of heterogeneity. floor=0 is the bare rule, under which a stratum that looks pure is never drawn again."""
    return share_out({h: sizes[h] * sqrt(max(0.0, heterogeneity.get(h, 0.0))) for h in sizes}, left, n, floor)


def by_rate(sizes: dict, valid: dict, drawn: dict, n: int, left: dict, floor: int = 1) -> dict:
    """By size times the smoothed valid rate, so that no stratum is out of reach."""
    return share_out({h: sizes[h] * (valid.get(h, 0) + 1) / (drawn.get(h, 0) + 2) for h in sizes}, left, n, floor)


def priority(rates: Numbers, sizes: dict) -> dict:
    """1 for the stratum to draw from first: highest valid rate, then larger, then by id."""
    order = sorted(sizes, key=lambda h: (-rates.get(h, 0.0), -sizes[h], h))
    return {h: i + 1 for i, h in enumerate(order)}
