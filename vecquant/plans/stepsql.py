"""The first iterations of the search as SQL, over fixed draws: an independent statement of the fit."""

from __future__ import annotations

import numpy as np

from vecquant.functions import curves
from vecquant.operators.fit import default_hparams, normals, rank_utilities
from vecquant.plans import sqltext as q
from vecquant.schema import GAIN_CAP

SAMPLES, _, RATE = default_hparams(2)
#: Start spreads that keep slopes away from zero, where gains are alike but for rounding.
SIGMA = {"kuma": (0.5, 0.5), "logi": (1.0, 0.25), "pwl": (1.0, 0.25)}


def draws(iterations: int) -> tuple:
    """Fixed normal draws [iterations][samples][2], to three places."""
    made = [np.round(normals(np.array([11]), 5, t, SAMPLES)[0].clip(-1.5, 1.5), 3) for t in range(iterations)]
    return tuple(tuple((float(a), float(b)) for a, b in one) for one in made)


def _allowed(curve: str, p0: str, p1: str) -> str:
    """The nearest allowed parameters, over lo and hi."""
    floor = q.num(curves.FLOOR)
    second = f"greatest({p1}, {floor})" if curve == "kuma" else f"least(greatest({p1}, lo / (hi - lo)), hi / (hi - lo))"
    return f"greatest({p0}, {floor}) AS p0, {second} AS p1"


def steps(curve: str, bits: int, iterations: int, name: str = "") -> str:
    """CTEs that end in fitted{name}: vec_id, p0, p1, gain after the iterations. Needs the long form first."""
    n = name or ""
    util = ", ".join(f"({k + 1}, {q.num(float(u))})" for k, u in enumerate(rank_utilities(SAMPLES)))
    (a, b), (s0, s1) = curves.START[curve], SIGMA[curve]
    gain = f"CASE WHEN isfinite(loss) THEN CASE WHEN loss = 0 THEN {GAIN_CAP} ELSE least(u / loss, {GAIN_CAP}) END ELSE 0 END"
    parts = [
        f"util{n} AS (SELECT * FROM (VALUES {util}) t(k, w))",
        f"flat{n} AS (SELECT vec_id, lo, hi, sum({q.error('unif', bits, coded=q.code('unif', bits))}) AS u FROM long GROUP BY vec_id, lo, hi)",
        f"at{n}0 AS (SELECT vec_id, lo, hi, u, {_allowed(curve, q.num(a), q.num(b))}, {q.num(s0)} AS s0, {q.num(s1)} AS s1 FROM flat{n})",
    ]
    for t, table in enumerate(draws(iterations)):
        z = ", ".join(f"({j}, {q.num(x)}, {q.num(y)})" for j, (x, y) in enumerate(table))
        parts += [
            f"draw{n}{t} AS (SELECT * FROM (VALUES {z}) t(j, z0, z1))",
            f"tried{n}{t} AS (SELECT vec_id, lo, hi, u, j, z0, z1, {_allowed(curve, 'p0 + s0 * z0', 'p1 + s1 * z1')} FROM at{n}{t}, draw{n}{t})",
            f"coded{n}{t} AS (SELECT tried{n}{t}.*, value, {q.code(curve, bits, 'p0', 'p1', lo='tried' + n + str(t) + '.lo', hi='tried' + n + str(t) + '.hi')} AS code FROM tried{n}{t} JOIN (SELECT vec_id, value FROM long) v USING (vec_id))",
            f"lost{n}{t} AS (SELECT vec_id, j, z0, z1, u, sum({q.error(curve, bits, 'p0', 'p1')}) AS loss FROM coded{n}{t} GROUP BY vec_id, j, z0, z1, u)",
            f"ranked{n}{t} AS (SELECT vec_id, z0, z1, row_number() OVER (PARTITION BY vec_id ORDER BY round({gain}, 9) DESC, j) AS k FROM lost{n}{t})",
            f"moved{n}{t} AS (SELECT vec_id, sum(w * z0) AS m0, sum(w * z1) AS m1, sum(w * (z0 * z0 - 1)) AS e0, sum(w * (z1 * z1 - 1)) AS e1 FROM ranked{n}{t} JOIN util{n} USING (k) GROUP BY vec_id)",
            f"at{n}{t + 1} AS (SELECT vec_id, lo, hi, u, {_allowed(curve, 'p0 + s0 * m0', 'p1 + s1 * m1')}, s0 * exp({q.num(RATE / 2)} * e0) AS s0, s1 * exp({q.num(RATE / 2)} * e1) AS s1 FROM at{n}{t} JOIN moved{n}{t} USING (vec_id))",
        ]
    last = f"at{n}{iterations}"
    parts += [
        f"final{n} AS (SELECT {last}.*, value, {q.code(curve, bits, 'p0', 'p1', lo=last + '.lo', hi=last + '.hi')} AS code FROM {last} JOIN (SELECT vec_id, value FROM long) v USING (vec_id))",
        f"summed{n} AS (SELECT vec_id, p0, p1, u, sum({q.error(curve, bits, 'p0', 'p1')}) AS loss FROM final{n} GROUP BY vec_id, p0, p1, u)",
        f"fitted{n} AS (SELECT vec_id, p0, p1, {gain} AS gain FROM summed{n})",
    ]
    return ", ".join(parts)
