"""Cost, memory and communication models.  Lists of a key have ``a`` (left) and ``b`` (right) rows; ``lam`` is the cost of a byte over the network in units of a byte on local disk."""

from __future__ import annotations

import math


def balance_exponent(a: float, b: float) -> float:
    """Exponent p of the sub-list length that gives splitter and followers equal work."""
    low, high = min(a, b), max(a, b)
    if low <= 1:
        return 2 / 3
    x = math.log(high, low)
    return (1 + x) / (1 + 2 * x)


def cube_root_ceil(n: int) -> int:
    r = round(n ** (1 / 3))
    while r**3 < n:
        r += 1
    while r and (r - 1) ** 3 >= n:
        r -= 1
    return r


def splitter_work(a: float, b: float, p: float) -> float:
    return (a * b) ** (1 - p) * max(a**p, b**p)


def follower_work(a: float, b: float, p: float) -> float:
    return (a * b) ** p


def delta_shuffle(l: float) -> float:
    """Time to write all pairs of a key of ``l`` rows on each side by one task."""
    return l**2


def delta_staged(l: float, lam: float, n: int) -> float:
    return ((1 + lam) + math.ceil(l ** (2 / 3) / n)) * l ** (4 / 3)


def worth_chunking(l: float, lam: float, n: int) -> bool:
    return delta_shuffle(l) > delta_staged(l, lam, n)


def hot_threshold(lam: float) -> float:
    return (1 + lam) ** 1.5


def hot_threshold_exact(lam: float, n: int) -> float:
    """The same without leaving out the followers' share on ``n`` executors (n > 1)."""
    return ((1 + lam) * n / (n - 1)) ** 1.5


def level_bound(l_max: float, lam: float) -> float:
    """The number of levels is below this."""
    if l_max <= 1 or lam <= 0:
        return 0.0
    inner = math.log(l_max, 1 + lam)
    return math.log(inner, 1.5) - 1 if inner > 0 else 0.0


def chunk_example(l: int, lam: float = 7.4125) -> dict[str, float]:
    """Sub-lists, followers, rows written by splitter and follower, and the splitting's share of all output in percent."""
    parts = cube_root_ceil(l)
    size = -(-l // parts)
    return {"sublists": parts, "sublist_length": size, "followers": parts**2, "splitter_rows": 2 * parts * parts * size, "follower_rows": 2 * size**2, "overhead_percent": 100 * (1 + lam) * parts * parts * size / l**2 / (1 + lam)}


def mem_grid_mapper(m_left: float, m_right: float, n: int) -> float:
    return max(m_left, m_right) * (1 + math.sqrt(n))


def mem_grid_reducer(a: float, b: float, m_left: float, m_right: float, n: int) -> float:
    return (a * m_left + b * m_right) / math.sqrt(n) + a * b * (m_left + m_right) / n


def mem_basic_splitter(a: float, b: float, m_left: float, m_right: float) -> float:
    return a * m_left + b * m_right + (a * b) ** (1 / 3) * (a ** (2 / 3) * m_left + b ** (2 / 3) * m_right)


def mem_follower(a: float, b: float, m_left: float, m_right: float, does: str = "chunk") -> float:
    own = a ** (2 / 3) * m_left + b ** (2 / 3) * m_right
    if does == "emit":
        return own + (a * b) ** (2 / 3) * (m_left + m_right)
    return own + (a * b) ** (2 / 9) * (a ** (4 / 9) * m_left + b ** (4 / 9) * m_right)


def mem_balanced_splitter(a: float, b: float, m_left: float, m_right: float) -> float:
    return max(m_left * (1 + b ** (1 / 3)), m_right * (1 + a ** (1 / 3)))


def delta_broadcast(n_small: float, m_small: float, lam: float, n: int) -> float:
    return n_small * m_small * (1 + lam * math.log(max(n, 1), lam + 1) if lam > 0 else 1)


def delta_split(n_big: float, m_big: float, lam: float) -> float:
    return n_big * m_big * (1 + lam)


def prefer_broadcast(n_big: float, m_big: float, n_small: float, m_small: float, lam: float, n: int) -> bool:
    return delta_split(n_big, m_big, lam) >= delta_broadcast(n_small, m_small, lam, n)


def comm_ids(n: int, n_small: float, m_id: float, n_big: float, m_big: float, as_printed: bool = True) -> float:
    """Outer small-large join by ids of unmatched rows; ``as_printed=False`` leaves out hashing the large side."""
    return (n + 1) * n_small * m_id + (n_big * m_big if as_printed else 0)


def comm_rows(n: int, n_small: float, m_small: float) -> float:
    return n * n_small * m_small


def comm_keys(n: int, n_keys: float, m_key: float) -> float:
    return 2 * n * n_keys * m_key


def max_hot_keys(n_rows: float, memory: float, m_other: float, m_key: float, lam: float) -> int:
    """Hot keys that an executor can hold together with the fewer than threshold cold rows that each has on the other side."""
    return int(min(min(n_rows, memory / max(m_other, 1)) / hot_threshold(lam), memory / max(m_key, 1)))


def delta_hot_keys(n_rows: float, m_row: float, n: int, k_max: int, m_key: float, lam: float) -> float:
    return n_rows * m_row / n + k_max * m_key * lam * math.log(n)


def space_heavy_hitters(eps: float) -> float:
    return 1 / eps


def space_quantiles(eps: float, n_rows: float, n: int) -> float:
    return math.log(eps * n_rows / n) / eps
