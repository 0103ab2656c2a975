"""Monotone two-parameter curves from [lo, hi] onto [0, 1], and their inverses, in NumPy.

All functions broadcast: values have a last axis of dimensions, bounds and parameters a last
axis of one. Work is in double precision. The column twins are in `expr`.
"""

from __future__ import annotations

import math

import numpy as np

#: The least slope or exponent that can be inverted, and the curves' start values.
FLOOR = 1e-6
START = {"unif": (0.0, 0.0), "kuma": (1.0, 1.0), "logi": (4.0, 0.0), "logi2": (4.0, 0.0), "pwl": (4.0, 0.0)}
SPREAD = {"unif": (0.0, 0.0), "kuma": (0.5, 0.5), "logi": (2.0, 0.5), "logi2": (2.0, 0.5), "pwl": (2.0, 0.5)}
NAMES = ("kuma", "logi", "pwl")


def power(x: np.ndarray, c: np.ndarray, form: str = "pow") -> np.ndarray:
    """x to the power c for x >= 0; form "explog" takes exp(c log x), "poly" polynomials for both."""
    if form == "pow":
        return np.power(x, c)
    positive = x > 0
    safe = np.where(positive, x, 1.0)
    if form == "explog":
        out = np.exp(c * np.log(safe))
    else:
        from vecquant.functions.fastmath import exp_poly, log_poly

        out = exp_poly(c * log_poly(safe))
    return np.where(positive, out, np.where(c == 0, 1.0, 0.0))


def kumaraswamy(x: np.ndarray, a: np.ndarray, b: np.ndarray, form: str = "pow") -> np.ndarray:
    """Cumulative distribution on [0, 1]."""
    return 1 - power(1 - power(x, a, form), b, form)


def kumaraswamy_inverse(y: np.ndarray, a: np.ndarray, b: np.ndarray, form: str = "pow") -> np.ndarray:
    """Quantile function on [0, 1]."""
    return power(1 - power(1 - y, 1 / b, form), 1 / a, form)


def kumaraswamy_density(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a * b * np.power(x, a - 1) * np.power(1 - np.power(x, a), b - 1)


def logistic(x: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-alpha * (x - x0)))


def logit(y: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    return np.log(y / (1 - y)) / alpha + x0


def logistic2(x: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    """Logistic function of base 2."""
    return 1 / (1 + np.exp2(-alpha * (x - x0)))


def logit2(y: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    return np.log2(y / (1 - y)) / alpha + x0


def pwl_log2(z: np.ndarray) -> np.ndarray:
    """Piecewise-linear log2, exact at powers of two: from the binary mantissa and exponent."""
    mantissa, exponent = np.frexp(z)
    return 2 * (mantissa - 1) + exponent


def pwl_exp2(v: np.ndarray) -> np.ndarray:
    """Inverse of pwl_log2."""
    v = np.clip(v, -1000, 1000)
    exponent = np.floor(v + 1)
    return np.ldexp((v - exponent) / 2 + 1, exponent.astype(np.int64))


def pwl_logistic(x: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    z = pwl_exp2(alpha * (x - x0))
    return z / (z + 1)


def pwl_logit(y: np.ndarray, alpha: np.ndarray, x0: np.ndarray) -> np.ndarray:
    return pwl_log2(y / (1 - y)) / alpha + x0


_RAW = {"logi": (logistic, logit), "logi2": (logistic2, logit2), "pwl": (pwl_logistic, pwl_logit)}


def bend(curve: str, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, p0: np.ndarray, p1: np.ndarray, form: str = "pow") -> np.ndarray:
    """Values in [lo, hi] to [0, 1]. A constant (sub)vector bends to 0."""
    width = np.where(hi > lo, hi - lo, 1.0)
    if curve == "unif":
        return (x - lo) / width
    if curve == "kuma":
        return kumaraswamy(np.clip((x - lo) / width, 0, 1), p0, p1, form)
    raw = _RAW[curve][0]
    low = raw(lo / width, p0, p1)
    span = raw(hi / width, p0, p1) - low
    return (raw(x / width, p0, p1) - low) / np.where(hi > lo, span, 1.0)


def unbend(curve: str, y: np.ndarray, lo: np.ndarray, hi: np.ndarray, p0: np.ndarray, p1: np.ndarray, form: str = "pow") -> np.ndarray:
    """The inverse of bend."""
    width = np.where(hi > lo, hi - lo, 1.0)
    flat = hi <= lo
    if curve == "unif":
        return np.where(flat, lo, lo + y * width)
    if curve == "kuma":
        return np.where(flat, lo, lo + kumaraswamy_inverse(y, p0, p1, form) * width)
    raw, inverse = _RAW[curve]
    low = raw(lo / width, p0, p1)
    span = raw(hi / width, p0, p1) - low
    return np.where(flat, lo, width * inverse(span * y + low, p0, p1))


def project(curve: str, p0: np.ndarray, p1: np.ndarray, lo: np.ndarray, hi: np.ndarray, domain: str = "scaled") -> tuple[np.ndarray, np.ndarray]:
    """The nearest parameters that the curve allows.

    domain: the midpoint's range is [lo, hi] in units of hi - lo ("scaled") or as it is ("raw").
    """
    if curve in ("unif", "kuma"):
        return np.maximum(p0, FLOOR), np.maximum(p1, FLOOR)
    width = np.where(hi > lo, hi - lo, 1.0) if domain == "scaled" else 1.0
    return np.maximum(p0, FLOOR), np.clip(p1, lo / width, hi / width)


def raw_parameters(alpha: np.ndarray, x0: np.ndarray, width: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Slope and midpoint in the values' own units, for the same curve."""
    return alpha / width, x0 * width


def quantize(curve: str, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int, form: str = "pow") -> np.ndarray:
    """Codes 0 .. 2**bits - 1 as floats: the bent value on a uniform grid, halves rounded up."""
    top = 2**bits - 1
    return np.clip(np.floor(top * bend(curve, x, lo, hi, p0, p1, form) + 0.5), 0, top)


def reconstruct(curve: str, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int, form: str = "pow") -> np.ndarray:
    codes = quantize(curve, x, lo, hi, p0, p1, bits, form)
    return unbend(curve, codes / (2**bits - 1), lo, hi, p0, p1, form)


def loss(curve: str, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int, weights: np.ndarray | None = None) -> np.ndarray:
    """Squared error of the round trip, summed over the last axis; infinite where saturated."""
    with np.errstate(all="ignore"):
        error = (x - reconstruct(curve, x, lo, hi, p0, p1, bits)) ** 2
        total = (error if weights is None else error * weights).sum(axis=-1)
    return np.where(np.isfinite(total), total, np.inf)


class Held:
    """Rows held for many losses: those of a logistic curve, value by value in memory that is kept from call to call.

    Cuts of rows are taken in turn, so that what one cut needs stays in the cache. Work is by
    [values, pairs]: what belongs to a parameter pair lies along the inner axis.
    """

    #: Doubles of one temporary.
    _ROOM = 120_000

    def __init__(self, x: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> None:
        self.x, self.lo, self.hi, self.rooms = x, lo, hi, {}
        self.width = np.where(hi > lo, hi - lo, 1.0)
        self.scaled = np.ascontiguousarray((x / self.width).T)

    def _room(self, name: str, shape: tuple[int, ...], kind: type = np.float64) -> np.ndarray:
        """A temporary kept from call to call: fresh memory of this size costs more than the work in it."""
        size = math.prod(shape)
        if name not in self.rooms or self.rooms[name].size < size:
            self.rooms[name] = np.empty(size, dtype=kind)
        return self.rooms[name][:size].reshape(shape)

    def _long(self, bits: int) -> int:
        """Doubles that a parameter pair takes of a temporary."""
        return self.x.shape[1]

    def loss(self, curve: str, rows: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int) -> np.ndarray:
        """Losses [rows, samples] of parameters [rows, samples] on these rows, as `loss` gives them."""
        out, step = np.empty(p0.shape), max(1, self._ROOM // (p0.shape[1] * self._long(bits)))
        with np.errstate(all="ignore"):
            for a in range(0, len(rows), step):
                cut = slice(a, a + step)
                out[cut] = self._loss(curve, rows[cut], p0[cut], p1[cut], bits)
        return np.where(np.isfinite(out), out, np.inf)

    def _loss(self, curve: str, rows: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int) -> np.ndarray:
        if curve != "logi":
            raise ValueError(curve)
        pairs, top = np.repeat(rows, p0.shape[1]), 2**bits - 1
        a, b, width = p0.ravel(), p1.ravel(), self.width[pairs, 0]
        low = logistic(self.lo[pairs, 0] / width, a, b)
        span = logistic(self.hi[pairs, 0] / width, a, b) - low
        x, made, other = (self._room(name, (len(self.scaled), len(pairs))) for name in ("x", "made", "other"))
        self.scaled.take(pairs, axis=1, out=x, mode="clip")
        np.multiply(x, -a, out=made)
        made += a * b
        np.exp(made, out=made)
        made += 1
        np.divide(top / span, made, out=made)
        made += 0.5 - top * low / span
        np.clip(np.floor(made, out=made), 0, top, out=made)
        made *= span / top
        made += low
        made /= np.subtract(1, made, out=other)
        np.log(made, out=made)
        made *= 1 / a
        made += b
        made -= x
        made *= made
        return (made.sum(axis=0) * width**2).reshape(p0.shape)


class Ordered(Held):
    """Rows in order with their running sums, for losses that evaluate a curve at its levels and code
    boundaries alone: 2**(bits + 1) - 1 inversions a parameter pair, however long a row is.

    Values are held in cells: a row's bounds are 0 and `cells`. Work is by [levels, pairs].
    """

    #: A total below this share of the row's own squares is taken again value by value: differences of sums are too coarse for it.
    _SHARE = 1e-7
    _ROOM = 200_000
    #: A boundary above the lower bound, whatever the curve: values at the bounds have the first and last code.
    _LEAST = 1e-300

    def __init__(self, x: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> None:
        n, d = x.shape
        self.x, self.lo, self.hi, self.rooms, self.cells = x, lo, hi, {}, 4 * d
        self.width = np.where(hi > lo, hi - lo, 1.0)
        order = np.sort(x, axis=1)
        held = np.where(order < hi, np.minimum((order - lo) / self.width * self.cells, self.cells), self.cells)
        self.values = np.concatenate([held, np.full((n, 1), np.inf)], axis=1).ravel()
        shifted = held - self.cells / 2
        sums = np.concatenate([np.zeros((n, 1)), np.cumsum(shifted, axis=1)], axis=1)
        self.squares, self.total = (shifted**2).sum(axis=1), sums[:, -1]
        # How many values lie below a place, and twice their sum, fetched together.
        self.below = (np.arange(d + 1) + 2j * sums).ravel()
        wide = np.arange(n)[:, None] * (self.cells + 1)
        counts = np.bincount((wide + held.astype(np.intp)).ravel(), minlength=n * (self.cells + 1)).reshape(n, -1)
        begins = np.concatenate([np.zeros((n, 1), dtype=np.intp), np.cumsum(counts, axis=1)], axis=1)
        self.begins = (begins + np.arange(n)[:, None] * (d + 1)).ravel()

    def _places(self, marks: np.ndarray, wide: np.ndarray) -> np.ndarray:
        """Where in `values` each mark [marks, pairs] stands: before the first value of its row that is not below it. wide: each pair's first cell."""
        shape = marks.shape
        cell, place = self._room("cell", shape, np.intp), self._room("place", shape, np.intp)
        np.copyto(cell, marks, casting="unsafe")
        cell += wide
        self.begins.take(cell, out=place, mode="clip")
        found = self.values.take(place, out=self._room("found", shape), mode="clip")
        flat, left, whole = marks.ravel(), np.flatnonzero(np.less(found, marks, out=self._room("ahead", shape, np.bool_))), place
        place = whole.reshape(-1)
        place[left] += 1
        for _ in range(3):  # a cell holds few values: step on while they lie below
            left = left[self.values[place[left]] < flat[left]]
            place[left] += 1
        if len(left):  # crowded cells: halve what is left of them
            low, high = place[left], self.begins[cell.reshape(-1)[left] + 1]
            while (open_ := low < high).any():
                middle = (low + high) // 2
                under = self.values[middle] < flat[left]
                low, high = np.where(open_ & under, middle + 1, low), np.where(open_ & ~under, middle, high)
            place[left] = low
        return whole

    def _made(self, curve: str, rows: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int) -> np.ndarray:
        """Levels and, between them, code boundaries, in cells: [2**(bits + 1) - 1, pairs]."""
        steps = 2 * (2**bits - 1)
        y = np.arange(steps + 1)[:, None] / steps
        made, other = (self._room(name, (steps + 1, len(rows))) for name in ("made", "other"))
        if curve == "kuma":  # logarithms of the levels are the same for all pairs
            np.exp(np.divide(np.log(1 - y), p1, out=made), out=made)
            np.log(np.subtract(1, made, out=made), out=made)
            np.exp(np.divide(made, p0, out=made), out=made)
            made *= self.cells
            return made
        lo, hi, width = self.lo[rows, 0], self.hi[rows, 0], self.width[rows, 0]
        if curve not in ("logi", "pwl"):
            return (unbend(curve, y, lo, hi, p0, p1) - lo) / width * self.cells
        raw = _RAW[curve][0]
        low, high = raw(lo / width, p0, p1), raw(hi / width, p0, p1)
        np.multiply(y, high - low, out=made)
        made += low
        made /= np.subtract(1, made, out=other)
        if curve == "logi":
            np.log(made, out=made)
        else:
            odd = np.flatnonzero(~((low > 0) & ((high - low) + low < 1)))  # odds of nought or without end
            kept = pwl_log2(made[:, odd])
            # A double's bits, as a number, are its piecewise-linear logarithm.
            bits = made.view(np.int64)
            bits -= 1023 << 52
            np.copyto(other, bits, casting="unsafe")
            np.multiply(other, 2.0**-52, out=made)
            made[:, odd] = kept
        made /= p0
        made += p1
        made *= width  # rounded as `unbend` rounds it, which tells where bounds lie far from 0
        made -= lo
        made *= self.cells / width
        return made

    def _long(self, bits: int) -> int:
        return 2 ** (bits + 1)

    def _loss(self, curve: str, rows: np.ndarray, p0: np.ndarray, p1: np.ndarray, bits: int) -> np.ndarray:
        pairs, d = np.repeat(rows, p0.shape[1]), self.x.shape[1]
        shape = (2**bits - 1, len(pairs))
        made = self._made(curve, pairs, p0.ravel(), p1.ravel(), bits)
        marks = np.fmin(made[1::2], self.cells, out=self._room("marks", shape))
        np.maximum(marks, self._LEAST, out=marks)
        places = self._places(marks, pairs * (self.cells + 2))
        below = self.below.take(places, out=self._room("below", shape, np.complex128), mode="clip")
        # The sum over levels of level * (level * count - 2 * total), by parts.
        low, high = made[:-2:2], made[2::2]
        gap = np.add(low, high, out=self._room("gap", shape))
        gap -= self.cells
        gap *= below.real
        gap -= below.imag
        gap *= np.subtract(high, low, out=marks)
        top, own = made[-1] - self.cells / 2, self.squares[pairs]
        out = own + top * (top * d - 2 * self.total[pairs]) - gap.sum(axis=0)
        at, sample = np.nonzero((out < self._SHARE * own).reshape(p0.shape))
        out = (out * (self.width[pairs, 0] / self.cells) ** 2).reshape(p0.shape)
        if len(at):
            own = rows[at]
            out[at, sample] = loss(curve, self.x[own], self.lo[own], self.hi[own], p0[at, sample][:, None], p1[at, sample][:, None], bits)
        return out
