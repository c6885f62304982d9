"""Exact integer arithmetic for label, base and edge-label vectors.

All values are 64-bit integers, so sums have no rounding and any engine gives the same
numbers. The formulas are written as SQL text with the engine's integer division as a
parameter; ``div`` is Spark's.
"""

from __future__ import annotations

from functools import lru_cache

P = (1 << 31) - 1
UNIT = 1 << 16
ZIPF_BUCKETS = 16
ZIPF_EXPONENT = 2.0
#: Salts that keep the vectors of different purposes apart.
LABEL, BASE, EDGE = 1, 2, 3


def idiv(a: str, b: str, spark: bool = True) -> str:
    return f"(({a}) div ({b}))" if spark else f"(({a}) // ({b}))"


def uniform(label: str, k: int, salt: int) -> str:
    """A pseudo-random integer 0..65535 seeded by a label, for dimension ``k``."""
    s = f"((48271 * CAST({label} AS BIGINT) + {69621 * k + 40692 * salt + 12345}) % {P})"
    for _ in range(3):
        s = f"(({s} * {s} + 16807 * {s} + 1013904223) % {P})"
    return f"({s} % {UNIT})"


@lru_cache
def zipf_edges(buckets: int = ZIPF_BUCKETS, exponent: float = ZIPF_EXPONENT, top: int = UNIT) -> tuple[int, ...]:
    """Quantiles, at equal steps of probability, of a power law on [1, top]."""
    if abs(exponent - 1) < 1e-9:
        return tuple(round(top ** (i / buckets)) for i in range(buckets + 1))
    e = 1 - exponent
    return tuple(round((1 + i / buckets * (top**e - 1)) ** (1 / e)) for i in range(buckets + 1))


def label_value(label: str, k: int, salt: int = 1, dist: str = "uniform", kind: int = LABEL, buckets: int = ZIPF_BUCKETS, exponent: float = ZIPF_EXPONENT, spark: bool = True) -> str:
    """The k-th value of a label's vector, at least 1.

    ``zipf`` maps equal-area buckets of the uniform law onto those of the power law and keeps the
    position within the bucket.
    """
    u = uniform(label, k, 10 * salt + kind)
    if dist == "uniform":
        return f"(1 + {u})"
    q = zipf_edges(buckets, exponent)
    width = UNIT // buckets
    cases = " ".join(f"WHEN {idiv('_u', str(width), spark)} = {i} THEN greatest(1, {q[i]} + {idiv(f'{q[i + 1] - q[i]} * (_u % {width})', str(width), spark)})" for i in range(buckets))
    return f"(CASE {cases} END)".replace("_u", u)


def base_raw(label: str, k: int, salt: int) -> str:
    return f"(1 + {uniform(label, k, 10 * salt + BASE)})"


def base_values(label: str, d: int, norm: str = "l1", salt: int = 1, spark: bool = True) -> list[str]:
    """The 2d values of a label's base vector, in units of 1/65536.

    l1: the whole vector sums to about 1; l1_half: each half does; diag: one value for each half;
    l2: unit length (integer square root).
    """
    raw = [base_raw(label, k, salt) for k in range(2 * d)]
    if norm == "diag":
        pair = [base_raw(label, 0, salt), base_raw(label, 1, salt)]
        return [idiv(f"{pair[k // d]} * {UNIT}", f"{d} * ({pair[0]} + {pair[1]})", spark) for k in range(2 * d)]
    if norm == "l1_half":
        halves = [" + ".join(raw[:d]), " + ".join(raw[d:])]
        return [idiv(f"{raw[k]} * {UNIT}", halves[k // d], spark) for k in range(2 * d)]
    if norm == "l2":
        length = "CAST(floor(sqrt(CAST(" + " + ".join(f"{r} * {r}" for r in raw) + " AS DOUBLE))) AS BIGINT)"
        return [idiv(f"{r} * {UNIT}", length, spark) for r in raw]
    return [idiv(f"{r} * {UNIT}", " + ".join(raw), spark) for r in raw]


def normal_cdf(t: str) -> str:
    """The standard normal distribution function by a rational approximation of erf (error below 2e-7)."""
    x = f"(abs({t}) / 1.4142135623730951)"
    k = f"(1.0 / (1.0 + 0.3275911 * {x}))"
    poly = f"({k} * (0.254829592 + {k} * (-0.284496736 + {k} * (1.421413741 + {k} * (-1.453152027 + {k} * 1.061405429)))))"
    erf = f"(1.0 - {poly} * exp(-{x} * {x}))"
    return f"(0.5 * (1.0 + sign({t}) * {erf}))"


def draw(label: int, k: int, salt: int) -> int:
    """``uniform`` on the driver, for the few labels of patterns."""
    s = (48271 * label + 69621 * k + 40692 * salt + 12345) % P
    for _ in range(3):
        s = (s * s + 16807 * s + 1013904223) % P
    return s % UNIT


def label_vector(label: int, d: int, salt: int, dist: str, kind: int = LABEL) -> list[int]:
    out = []
    for k in range(d):
        u = draw(label, k, 10 * salt + kind)
        if dist == "uniform":
            out.append(1 + u)
        else:
            q = zipf_edges()
            width = UNIT // (len(q) - 1)
            i = u // width
            out.append(max(1, q[i] + (q[i + 1] - q[i]) * (u % width) // width))
    return out


def base_vector(label: int, d: int, norm: str, salt: int) -> list[int]:
    raw = [1 + draw(label, k, 10 * salt + BASE) for k in range(2 * d)]
    if norm == "diag":
        return [raw[k // d] * UNIT // (d * (raw[0] + raw[1])) for k in range(2 * d)]
    if norm == "l1_half":
        return [raw[k] * UNIT // sum(raw[k // d * d : k // d * d + d]) for k in range(2 * d)]
    if norm == "l2":
        return [r * UNIT // int(sum(x * x for x in raw) ** 0.5) for r in raw]
    return [r * UNIT // sum(raw) for r in raw]
