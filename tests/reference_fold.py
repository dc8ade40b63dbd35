"""A plain fold of a stream through each policy, written apart from the kernels."""

from __future__ import annotations


def fold(updates, policy, k, q=0.5, k_star=None):
    """Counters (dict) and what was subtracted, or the least counter for replacement."""
    table, offset = {}, 0
    for item, weight in updates:
        if item in table:
            table[item] += weight
            continue
        if len(table) < k:
            table[item] = weight
            continue
        if policy == "heap":
            least = min((c, i) for i, c in table.items())
            del table[least[1]]
            table[item] = least[0] + weight
            continue
        values = sorted(table.values())
        cut = {"rank": values[len(values) - (k_star or max(1, k // 2))], "quantile": values[min(int(q * k), k - 1)], "min": min(values[0], weight)}[policy]
        offset += cut
        table = {i: c - cut for i, c in table.items() if c > cut}
        if weight > cut:
            table[item] = weight - cut
    if policy == "heap":
        offset = min(table.values()) if len(table) >= k else 0
    return table, offset
