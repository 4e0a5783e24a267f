"""Formulas: memory, false positive bounds, lower bounds, infix probabilities, and which filter gives which guarantee."""

from __future__ import annotations

import math

#: Fixed values: (filter, robust, semi-robust, queries of any length, keys of any length, dynamic).
GOALS = (
    ("truncated_trie", False, False, True, True, False),
    ("dyadic_bloom", True, True, False, False, False),
    ("shared_dyadic_bitmap", False, False, False, False, False),
    ("prefix_hash_bitmap", False, False, False, False, False),
    ("tuned_trie_bloom", False, False, False, False, False),
    ("spline_bitmap", False, True, True, False, False),
    ("pruned_spline_bitmap", False, True, True, False, False),
    ("local_hash_set", True, True, False, False, False),
    ("prefix_suffix_table", True, True, False, False, True),
    ("prefix_suffix_table_extra_bit", True, True, False, False, True),
    ("base_filter", False, True, True, True, True),
    ("enhanced_filter", False, True, True, True, True),
)


def static_bound(eps: float, length: int) -> float:
    """Expected false positive rate on well-behaved data."""
    return eps if length == 1 else 2 * eps


def dynamic_bound(eps: float, n: int, length: int) -> float:
    """The same after n inserts without drift."""
    return eps * (math.log2(max(n, 1)) + 2) / (2 if length == 1 else 1)


def static_bpk(eps: float, key_bits: int = 64, t: int = 1024) -> float:
    """Two bitmaps, remainders of log2(2/eps) bits, and a share of an anchor."""
    return 2 + math.log2(2 / eps) + (96 + key_bits) / t if t != 1024 else 3.09 + key_bits / 1024 + math.log2(1 / eps)


def dynamic_bpk(eps: float, key_bits: int = 64, load: float = 0.95) -> float:
    return 1.09 + key_bits / 1024 + (2 + math.log2(1 / eps)) / load**2


def bpk(name: str, eps: float, length: int, load: float = 0.95, suffix: float = 4, inner: float = 0.0, trailing: float = 0.0) -> float:
    """Bits per key of a filter at a rate eps for ranges up to `length`; inner: trie nodes per key, trailing: extra trie bits per key."""
    e, r = math.log2(1 / eps), math.log2(length / eps)
    return {
        "truncated_trie": 10 + 10 * inner + suffix, "dyadic_bloom": 1.44 * r, "prefix_hash_bitmap": 1.2 * r, "tuned_trie_bloom": 10 * inner + 1.44 * e,
        "spline_bitmap": 2.4 + e, "pruned_spline_bitmap": 2.4 + e, "local_hash_set": 2 + r, "prefix_suffix_table": (3.125 + r) / load, "prefix_suffix_table_extra_bit": (4.125 + r) / load,
        "base_static": 3.19 + e, "base_dynamic": 1.19 + (2 + e) / load**2, "enhanced_static": 3.19 + trailing + e, "enhanced_dynamic": 1.19 + trailing + (2 + e) / load**2,
    }[name]


def lower_bound(kind: str, eps: float, length: int) -> float:
    """Leading term of the least bits per key: data_aware robust or semi_robust, data_oblivious, or both together."""
    return {"data_aware": math.log2(length / eps), "data_oblivious": math.log2(1 / eps), "combined": math.log2(length / eps) + math.log2(1 / eps)}[kind]


def max_range(budget: float, eps: float) -> int:
    """The longest range, a power of two, for which a robust filter can hold eps within a budget."""
    return 1 << max(0, math.floor(math.log2(eps * 2**budget)))


def infix_probability(eps: float, n: int, k: int = 1) -> float:
    """Chance that k given of n uniform keys fall on one given infix of a block: each does with eps / (2 n)."""
    p = eps / (2 * n)
    return math.comb(n, k) * p**k * (1 - p) ** (n - k) if n else 0.0


def well_behaved(densities: list[float], t: int, n: int) -> tuple[float, bool]:
    """(the largest relative change of density over a block's span, whether it is at most a quarter) of an equi-depth histogram."""
    steps = [abs(b - a) / max(a, b) for a, b in zip(densities, densities[1:], strict=False) if max(a, b) > 0]
    reach = min(1.0, t * math.log2(max(n, 2)) / max(n, 1) * max(1, len(densities)))
    alpha = max(steps, default=0.0) * reach
    return alpha, alpha <= 0.25
