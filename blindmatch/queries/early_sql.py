"""Early mapping as SQL: per round the edges, their parts, every one-to-one mapping of each part and the best of these.

An optimal mapping is found by enumeration, so this shares nothing with the solver that it is held against."""

from __future__ import annotations

from blindmatch.queries import workloads as W

_DICE = "CASE WHEN m.ones + n.ones > 0 THEN 2.0 * len(list_intersect(m.bits, n.bits)) / (m.ones + n.ones) ELSE 0 END"
_SCORES = {
    "average": f"round(avg({_DICE}), 12)",
    "min": f"min({_DICE})",
    "max": f"max({_DICE})",
    # The positions that all members and the arrival have.
    "cbf": "round((count(*) + 1) * len(list_intersect(list_reduce(list(m.bits), lambda a, b: list_intersect(a, b)), any_value(n.bits))) / (sum(m.ones) + any_value(n.ones)), 12)",
}
_ORDERS = {"size": "-count(*)", "random": "md5('7:' || party)"}


def sql_early(p: int, rate: int = 20, s_t: float = 0.8, how: str = "average", mapping: str = "optimal", ord: str = "size", masked: str | None = None) -> str:
    """CTEs up to ``assigned``: rec_id, cluster_id, cluster_size, entity_id."""
    out = [(masked or W.sql_masked(p, rate)).replace("WITH ", "WITH RECURSIVE ", 1)]
    out.append(f"places AS MATERIALIZED (SELECT party, row_number() OVER (ORDER BY {_ORDERS[ord]}, party) - 1 AS place FROM masked GROUP BY party)")
    out.append("recs AS MATERIALIZED (SELECT m.block, m.rec_id, m.entity_id, m.bits, m.ones, place FROM masked m JOIN places USING (party))")
    out.append("members0 AS MATERIALIZED (SELECT block, rec_id AS cluster, 0::BIGINT AS seed_place, rec_id, entity_id, bits, ones FROM recs WHERE place = 0)")
    scan = "w DESC, place, x, y" if mapping == "optimal" else "place, x, w DESC, y"
    free = "NOT list_contains(xs, e.x) AND NOT list_contains(ys, e.y)"
    allowed = f"NOT take OR ({free})" if mapping == "optimal" else f"take = ({free})"
    for i in range(1, p):
        was = f"members{i - 1}"
        out += [
            f"""edges{i} AS MATERIALIZED (SELECT m.block, m.cluster AS x, m.seed_place AS place, n.rec_id AS y, {_SCORES[how]} AS w
  FROM {was} m JOIN recs n ON m.block = n.block AND n.place = {i} GROUP BY m.block, m.cluster, m.seed_place, n.rec_id HAVING {_SCORES[how]} >= {s_t})""",
            f"""reach{i} AS (SELECT x AS a, x AS b FROM edges{i} UNION
  SELECT r.a, e2.x FROM reach{i} r JOIN edges{i} e1 ON e1.x = r.b JOIN edges{i} e2 ON e2.y = e1.y)""",
            f"parts{i} AS MATERIALIZED (SELECT a AS x, min(b) AS part FROM reach{i} GROUP BY a)",
            f"""ranked{i} AS MATERIALIZED (SELECT e.*, part, row_number() OVER (PARTITION BY part ORDER BY {scan}) AS r, count(*) OVER (PARTITION BY part) AS total
  FROM edges{i} e JOIN parts{i} USING (x))""",
            f"""picked{i} AS (SELECT DISTINCT part, 0::BIGINT AS r, []::BIGINT[] AS xs, []::BIGINT[] AS ys, 0::DOUBLE AS w, []::BIGINT[] AS chosen FROM ranked{i}
  UNION ALL
  SELECT e.part, e.r, CASE WHEN take THEN list_append(xs, e.x) ELSE xs END, CASE WHEN take THEN list_append(ys, e.y) ELSE ys END,
    CASE WHEN take THEN q.w + e.w ELSE q.w END, CASE WHEN take THEN list_append(chosen, e.r) ELSE chosen END
  FROM picked{i} q JOIN ranked{i} e ON e.part = q.part AND e.r = q.r + 1, (VALUES (true), (false)) AS t(take) WHERE {allowed})""",
            f"""best{i} AS MATERIALIZED (SELECT q.*, row_number() OVER (PARTITION BY part ORDER BY round(q.w, 9) DESC, chosen) AS place
  FROM picked{i} q JOIN (SELECT DISTINCT part, total FROM ranked{i}) n USING (part) WHERE q.r = n.total)""",
            f"taken{i} AS MATERIALIZED (SELECT unnest(xs) AS x, unnest(ys) AS y FROM best{i} WHERE place = 1)",
            f"""members{i} AS MATERIALIZED (SELECT * FROM {was} UNION ALL
  SELECT n.block, coalesce(t.x, n.rec_id), coalesce(c.seed_place, {i}), n.rec_id, n.entity_id, n.bits, n.ones FROM recs n
  LEFT JOIN taken{i} t ON t.y = n.rec_id LEFT JOIN (SELECT DISTINCT cluster, seed_place FROM {was}) c ON c.cluster = t.x WHERE n.place = {i})""",
        ]
    out.append(f"assigned AS (SELECT rec_id, cluster AS cluster_id, CAST(count(*) OVER (PARTITION BY cluster) AS INTEGER) AS cluster_size, entity_id FROM members{p - 1})")
    return ",\n".join(out)


def sql_clusters(p: int, **how) -> str:
    return f"{sql_early(p, **how)}\nSELECT rec_id, cluster_id, cluster_size FROM assigned"


def sql_quality(ctes: str, assigned: str, s_m: int = 2, tags: str = "") -> str:
    """Pair quality of a table of clusters (cluster_id, cluster_size, entity_id); ``tags`` are leading columns."""
    return f"""SELECT {tags}tm, pairs - tm AS fm, greatest(0, true_pairs - tm) AS fn, round(CASE WHEN pairs > 0 THEN tm / pairs ELSE 0 END, 6) AS precision,
  round(CASE WHEN true_pairs > 0 THEN tm / greatest(tm, true_pairs) ELSE 0 END, 6) AS recall, round(CASE WHEN tm > 0 THEN 2 * tm / (pairs + greatest(tm, true_pairs)) ELSE 0 END, 6) AS f FROM ({ctes}
SELECT (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT FROM (SELECT count(*) AS n FROM {assigned} WHERE cluster_size >= {s_m} GROUP BY cluster_id, entity_id)) AS tm,
  (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT FROM (SELECT count(*) AS n FROM {assigned} WHERE cluster_size >= {s_m} GROUP BY cluster_id)) AS pairs,
  (SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT FROM (SELECT count(*) AS n FROM {assigned} GROUP BY entity_id) WHERE n >= {s_m}) AS true_pairs)"""
