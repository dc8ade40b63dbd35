"""SQL that plays a stream through a policy update by update, to hold kernels against."""

from __future__ import annotations


def replay(stream: str, policy: str, k: int, q: float = 0.5, k_star: int | None = None, item_type: str = "BIGINT") -> str:
    """item, c, offset after all updates of `stream`, a query with item, weight and ord.

    The state is a list of counters in the order of their arrival and what was subtracted so far. Tables
    of more counters than a sample holds are beyond this.
    """
    pair = f"STRUCT(item {item_type}, c BIGINT)"
    values = "list_sort([x.c FOR x IN t])"
    cut = {
        "rank": f"({values})[{k} - {k_star or max(1, k // 2)} + 1]",
        "sample_quantile": f"({values})[least(CAST(floor({q} * {k}) AS INTEGER), {k - 1}) + 1]",
        "global_min": f"least(w, ({values})[1])",
        "unit_decrement": "1",
    }.get(policy)
    if policy == "space_saving_heap":
        least = "list_sort([{'c': x.c, 'item': x.item} FOR x IN t])[1]"
        full = f"list_append([x FOR x IN t IF x.item <> v.item], CAST({{'item': i, 'c': v.c + w}} AS {pair}))"
        step, extra, offset = full, f"{least} AS v", "off"
    else:
        full = f"list_concat([CAST({{'item': x.item, 'c': x.c - d}} AS {pair}) FOR x IN t IF x.c > d], CASE WHEN w > d THEN [CAST({{'item': i, 'c': w - d}} AS {pair})] ELSE [] END)"
        step, extra, offset = full, f"CAST({cut} AS BIGINT) AS d", "CASE WHEN hit OR len(t) < {k} THEN off ELSE off + d END".format(k=k)
    last = "CASE WHEN (SELECT len(t) FROM f) >= {k} THEN (SELECT min(x.c) FROM (SELECT unnest(t) AS x FROM f)) ELSE 0 END".format(k=k) if policy == "space_saving_heap" else "(SELECT off FROM f)"
    return f"""
WITH RECURSIVE u AS (SELECT row_number() OVER (ORDER BY ord) AS rn, item AS i, weight AS w FROM ({stream})),
r(n, t, off) AS (
  SELECT CAST(0 AS BIGINT), CAST([] AS {pair}[]), CAST(0 AS BIGINT)
  UNION ALL
  SELECT rn,
    CASE WHEN hit THEN [CASE WHEN x.item = i THEN CAST({{'item': x.item, 'c': x.c + w}} AS {pair}) ELSE x END FOR x IN t]
         WHEN len(t) < {k} THEN list_append(t, CAST({{'item': i, 'c': w}} AS {pair}))
         ELSE {step} END,
    {offset}
  FROM (SELECT rn, t, off, i, w, list_contains([x.item FOR x IN t], i) AS hit, {extra} FROM r JOIN u ON u.rn = r.n + 1)
), f AS (SELECT t, off FROM r ORDER BY n DESC LIMIT 1)
SELECT x.item AS item, x.c AS c, CAST({last} AS BIGINT) AS "offset" FROM (SELECT unnest(t) AS x FROM f)
"""
