"""DuckDB SQL for both selectors in full: growth and greedy choice as recursive CTEs, rounds unrolled one after another.

Every text starts from a CTE `ev` with etype and t. It shares nothing with the engine: occurrences are rows with their lists, the
best extension is a window's first rank, and a greedy pick updates all scores left. A fixed number of rounds is written out; a
selection that takes more would differ from the SQL's rows, so it would be noticed.
"""

from __future__ import annotations

_LABEL = "concat(types[1], array_to_string(list_transform(range(1, size), lambda i: concat('+', gaps[i], '>', types[i + 1])), ''))"
_TIES = "size DESC, span, types, gaps"


def _met(grown: str, events: str, tg: int, over: str) -> str:
    """All one-event extensions of the grown occurrences by a type they lack, with each kind's count."""
    return f"""SELECT w.*, e.t AS t2, e.etype AS e2, CAST(x.g AS INT) AS g, count(*) OVER (PARTITION BY {over}, e.etype, x.g) AS n2
        FROM {grown} w CROSS JOIN (SELECT unnest(range(1, {tg + 1})) AS g) x JOIN {events} e ON e.t = w.t + x.g WHERE NOT list_contains(w.types, e.etype)"""


def greedy_paths(r: str, events: str, tg: int = 5, rule: str = "score_improves") -> str:
    """CTE found{r}: occurrences (key, s, types, gaps, size, n) of the path-greedy candidates."""
    better = "" if rule == "frequency_floor" else " AND n2 * (size + 1) - (2 * (size + 1) + n2 + 1) > n * size - (2 * size + n + 1)"
    return f"""grow{r}(path, s, t, types, gaps, size, n) AS (
        SELECT etype, t, t, [etype], CAST([] AS INT[]), 1, count(*) OVER (PARTITION BY etype) FROM {events}
        UNION ALL SELECT path, s, t2, list_append(types, e2), list_append(gaps, g), size + 1, n2
        FROM (SELECT *, rank() OVER (PARTITION BY path ORDER BY n2 DESC, g, e2) AS place FROM ({_met(f'grow{r}', events, tg, 'w.path')}))
        WHERE place = 1 AND (n2 * size > 2 * size + 3 OR (n2 * size = 2 * size + 3 AND g < {tg})){better}),
    found{r} AS MATERIALIZED (SELECT {_LABEL} AS key, s, types, gaps, size, n FROM (SELECT *, max(size) OVER (PARTITION BY path) AS top FROM grow{r}) WHERE size = top AND size > 1 AND n * size > 2 * size + n + 1)"""


def all_frequent(r: str, events: str, fth: float, tg: int = 5, longest: int | None = None) -> str:
    """CTE found{r}: occurrences of every frequent multi-node episode."""
    least = f"{fth} * (SELECT count(*) FROM {events})"
    return f"""grow{r}(s, t, types, gaps, size, n) AS (
        SELECT * FROM (SELECT t, t, [etype], CAST([] AS INT[]), 1, count(*) OVER (PARTITION BY etype) AS n FROM {events}) WHERE n >= {least}
        UNION ALL SELECT s, t2, list_append(types, e2), list_append(gaps, g), size + 1, n2 FROM ({_met(f'grow{r}', events, tg, 'w.types, w.gaps')}) WHERE n2 >= {least}{f" AND size < {longest}" if longest else ""}),
    found{r} AS MATERIALIZED (SELECT {_LABEL} AS key, s, types, gaps, size, n FROM grow{r} WHERE size > 1)"""


def closed(r: str, of: str) -> str:
    """CTEs shorter{r} (key, n of a longer episode) and closed{r}, maximal{r} (keys), from the occurrences `of`."""
    return f"""eps{r} AS MATERIALIZED (SELECT DISTINCT key, types, gaps, size, n FROM {of}), cut{r} AS (SELECT *, unnest(range(1, size + 1)) AS i FROM eps{r} WHERE size > 2),
    shorter{r} AS MATERIALIZED (SELECT {_LABEL} AS key, n FROM (SELECT n, size - 1 AS size, list_concat(types[1:i - 1], types[i + 1:]) AS types,
        CASE WHEN i = 1 THEN gaps[2:] WHEN i = size THEN gaps[1:size - 2] ELSE list_concat(list_append(gaps[1:i - 2], gaps[i - 1] + gaps[i]), gaps[i + 1:]) END AS gaps FROM cut{r})),
    closed{r} AS (SELECT key FROM eps{r} WHERE (key, n) NOT IN (SELECT key, n FROM shorter{r})), maximal{r} AS (SELECT key FROM eps{r} WHERE key NOT IN (SELECT key FROM shorter{r}))"""


def picks(r: str, of: str, left: str | None = None, most: int | None = None, penalise: bool = True) -> str:
    """CTEs cand{r}, cover{r} and pick{r} (place, key, value, types, gaps, size, n): the greedy choice among useful candidates."""
    shared = "coalesce(o.shared, 0)" if penalise else "0"
    limit = f" ORDER BY score DESC, {_TIES} LIMIT {most}" if most else ""
    stop = f" AND place < {left}" if left else ""
    first = f"(ORDER BY value DESC, {_TIES})"
    return f"""cand{r} AS MATERIALIZED (SELECT key, types, gaps, size, n, n * size - (2 * size + n + 1) AS score, coalesce(list_sum(gaps), 0) AS span FROM {of} GROUP BY ALL HAVING score > 0{limit}),
    cover{r} AS MATERIALIZED (SELECT key, unnest(types) AS etype, s + unnest(list_transform(range(size), lambda i: coalesce(list_sum(gaps[1:i]), 0))) AS t FROM {of} WHERE key IN (SELECT key FROM cand{r})),
    shared{r} AS MATERIALIZED (SELECT a.key AS a, b.key AS b, count(*) AS shared FROM cover{r} a JOIN cover{r} b ON a.etype = b.etype AND a.t = b.t AND a.key <> b.key GROUP BY 1, 2),
    turn{r}(place, key, value, best, top) AS (
        SELECT 0, key, value, first_value(key) OVER {first}, first_value(value) OVER {first} FROM (SELECT *, CAST(score AS BIGINT) AS value FROM cand{r})
        UNION ALL SELECT place + 1, key, value, first_value(key) OVER {first}, first_value(value) OVER {first}
        FROM (SELECT w.place, w.key, w.value - {shared} AS value, c.size, c.span, c.types, c.gaps FROM turn{r} w JOIN cand{r} c ON c.key = w.key LEFT JOIN shared{r} o ON o.a = w.best AND o.b = w.key WHERE w.key <> w.best AND w.top > 0)),
    pick{r} AS MATERIALIZED (SELECT place, w.key, w.value, types, gaps, size, n FROM turn{r} w JOIN cand{r} c ON c.key = w.key WHERE w.key = w.best AND w.value > 0{stop})"""


def selection(ev: str, rounds: int, rule: str = "score_improves", fth: float | None = None, k: int | None = None, most: int | None = None, penalise: bool = True, tg: int = 5, longest: int | None = None) -> str:
    """WITH text up to the CTEs chosen (round, rank, score, size, n_occ, episode), rest (etype, t) and steps (the trace)."""
    out, events = [ev], "ev"
    for i in range(1, rounds + 1):
        r = str(i)
        out.append(greedy_paths(r, events, tg, rule) if fth is None else all_frequent(r, events, fth, tg, longest))
        before = " - ".join([str(k), *(f"(SELECT count(*) FROM pick{j})" for j in range(1, i))]) if k is not None else None
        out.append(picks(r, f"found{r}", before, most, penalise))
        out.append(f"left{r} AS MATERIALIZED (SELECT etype, t FROM {events} EXCEPT SELECT etype, t FROM cover{r} WHERE key IN (SELECT key FROM pick{r}))")
        events = f"left{r}"
    union = " UNION ALL ".join(f"SELECT {i} AS round, place, key, value, size, n FROM pick{i}" for i in range(1, rounds + 1))
    out.append(f"chosen AS MATERIALIZED (SELECT round, CAST(row_number() OVER (ORDER BY round, place) AS INT) AS rank, value AS score, CAST(size AS INT) AS size, n AS n_occ, key AS episode FROM ({union}))")
    out.append(f"rest AS (SELECT etype, t FROM {events})")
    steps = " UNION ALL ".join(f"SELECT {i} AS round, (SELECT count(DISTINCT key) FROM found{i}) AS n_found, (SELECT count(*) FROM cand{i}) AS n_useful, (SELECT count(*) FROM pick{i}) AS n_picked, (SELECT count(*) FROM left{i}) AS events_left" for i in range(1, rounds + 1))
    out.append(f"steps AS (SELECT * FROM ({steps}))")
    return "WITH RECURSIVE " + ",\n    ".join(out)


UNITS = "(SELECT coalesce(sum(2 * size + n_occ + 1), 0) FROM chosen) + (SELECT count(*) + 3 * count(DISTINCT etype) FROM rest)"
