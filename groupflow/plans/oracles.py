"""DuckDB SQL with the results of the registered queries, composed of named steps."""

from __future__ import annotations

from groupflow.params import Params
from groupflow.sources.tracks import EVENT_ORIGIN, HOUR


def steps(p: Params) -> dict[str, str]:
    """Named common table expressions in an order in which each reads earlier ones only."""
    e2, g = p.eps * p.eps, p.max_gap
    out = {
        "fixes": f"""SELECT user_id AS obj_id, event_id, ts, value AS x, (props->>'$.k')::DOUBLE AS y,
            (epoch_us(ts) - {EVENT_ORIGIN})::DOUBLE / {HOUR}::DOUBLE AS e FROM events
            WHERE user_id IS NOT NULL AND ts IS NOT NULL AND value IS NOT NULL AND props->>'$.k' IS NOT NULL""",
        "legs": """SELECT *, lead(x) OVER o AS x2, lead(y) OVER o AS y2, lead(e) OVER o AS e2 FROM fixes
            WINDOW o AS (PARTITION BY obj_id ORDER BY ts, event_id)""",
        "snap": """SELECT t, obj_id, CASE WHEN t = e THEN x ELSE x + (x2 - x) * ((t - e) / (e2 - e)) END AS x,
            CASE WHEN t = e THEN y ELSE y + (y2 - y) * ((t - e) / (e2 - e)) END AS y
            FROM (SELECT *, unnest(generate_series(ceil(e)::BIGINT,
              CASE WHEN e2 IS NULL THEN floor(e) ELSE ceil(e2) - 1 END::BIGINT)) AS t FROM legs)""",
        "near": f"""SELECT a.t, a.obj_id, b.obj_id AS other FROM snap a JOIN snap b ON a.t = b.t
            AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {e2}::DOUBLE""",
        "core": f"SELECT t, obj_id FROM near GROUP BY t, obj_id HAVING count(*) >= {p.min_pts}",
        "joined": """SELECT n.t, n.obj_id AS a, n.other AS b FROM near n
            JOIN core c ON c.t = n.t AND c.obj_id = n.obj_id JOIN core o ON o.t = n.t AND o.obj_id = n.other""",
        "together": """SELECT t, a, b FROM joined UNION
            SELECT r.t, r.a, j.b FROM together r JOIN joined j ON r.t = j.t AND r.b = j.a""",
        "labels": "SELECT t, a AS obj_id, min(b) AS low FROM together GROUP BY t, a",
        "everyone": """SELECT t, obj_id, low, true AS is_core FROM labels UNION ALL
            SELECT n.t, n.obj_id, min(l.low), false FROM near n JOIN labels l ON l.t = n.t AND l.obj_id = n.other
            WHERE NOT EXISTS (SELECT 1 FROM core c WHERE c.t = n.t AND c.obj_id = n.obj_id) GROUP BY n.t, n.obj_id""",
        "member": f"""SELECT e.t, e.t * 4294967296 + e.low AS cluster_id, e.obj_id, s.x, s.y, e.is_core
            FROM everyone e JOIN snap s ON s.t = e.t AND s.obj_id = e.obj_id
            QUALIFY count(*) OVER (PARTITION BY e.t, e.low) >= {p.m_c}""",
        "middle": """SELECT cluster_id, t, count(*) AS n, sum(x ORDER BY obj_id) / count(*) AS mx, sum(y ORDER BY obj_id) / count(*) AS my,
            min(x) AS minx, max(x) AS maxx, min(y) AS miny, max(y) AS maxy FROM member GROUP BY cluster_id, t""",
        "shape": """SELECT m.*, max(sqrt((p.x - m.mx) ** 2 + (p.y - m.my) ** 2)) AS r,
            avg((p.x - m.mx) ** 2 + (p.y - m.my) ** 2) AS var
            FROM middle m JOIN member p USING (cluster_id) GROUP BY ALL""",
        "gaps": f"""SELECT a.cluster_id AS src, b.cluster_id AS dst, b.t - a.t AS dt, a.obj_id AS ao, b.obj_id AS bo,
            (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS q
            FROM member a JOIN (SELECT *, unnest(range(1, {g + 1})) AS gap FROM member) b ON a.t = b.t - b.gap""",
        "hausdorff": """SELECT src, dst, dt, max(q) AS q FROM (
              SELECT src, dst, dt, min(q) AS q FROM gaps GROUP BY src, dst, dt, ao
              UNION ALL SELECT src, dst, dt, min(q) FROM gaps GROUP BY src, dst, dt, bo) GROUP BY src, dst, dt""",
        "link": f"SELECT src, dst, dt FROM hausdorff WHERE q <= ({p.d}::DOUBLE * dt) * ({p.d}::DOUBLE * dt)",
        "cover": """SELECT l.src, l.dst, l.dt FROM link l WHERE NOT EXISTS (
            SELECT 1 FROM link x JOIN link y ON x.dst = y.src WHERE x.src = l.src AND y.dst = l.dst)""",
        "bounds": "SELECT min(t) AS lo, max(t) AS hi FROM shape",
        "nodes": """SELECT s.cluster_id, s.t, (SELECT max(s.t - c.dt) FROM cover c WHERE c.dst = s.cluster_id) AS last_pred,
            (SELECT min(s.t + c.dt) FROM cover c WHERE c.src = s.cluster_id) AS first_succ FROM shape s""",
        "paths": f"""SELECT [cluster_id] AS path, t AS first_t, last_pred, cluster_id AS tail, t AS tail_t FROM nodes
            UNION ALL SELECT list_append(p.path, c.dst), p.first_t, p.last_pred, c.dst, p.tail_t + c.dt
            FROM paths p JOIN cover c ON c.src = p.tail WHERE p.tail_t + c.dt - p.first_t < {p.w}""",
        "crowd": f"""SELECT * FROM (SELECT array_to_string(path, '-') AS crowd_id, path, len(path) AS len,
            greatest(p.tail_t - {p.w} + 1, p.last_pred + 1, b.lo) AS s_lo,
            least(p.first_t, n.first_succ - {p.w}, b.hi - {p.w} + 1) AS s_hi
            FROM paths p JOIN nodes n ON n.cluster_id = p.tail, bounds b WHERE len(path) >= {p.k_c}) WHERE s_lo <= s_hi""",
        "alive0": "SELECT crowd_id, s_lo, s_hi, unnest(path) AS cluster_id FROM crowd",
    }
    rounds = p.w - p.k_c + 1
    for k in range(rounds + 1):
        out[f"real{k}"] = f"""SELECT a.crowd_id, m.obj_id, count(*) AS cnt FROM alive{k} a JOIN member m USING (cluster_id)
            GROUP BY a.crowd_id, m.obj_id HAVING count(*) >= {p.k_p}"""
        if k < rounds:
            out[f"alive{k + 1}"] = f"""SELECT a.* FROM alive{k} a WHERE (SELECT count(*) FROM member m JOIN real{k} r
                ON r.obj_id = m.obj_id WHERE m.cluster_id = a.cluster_id AND r.crowd_id = a.crowd_id) >= {p.m_p}"""
    out |= {
        "agg": f"""SELECT c.*, m.members, len(m.members) AS size FROM (
              SELECT crowd_id, s_lo, s_hi, list(cluster_id ORDER BY cluster_id) AS path,
                array_to_string(list(cluster_id ORDER BY cluster_id), '-') AS agg_id
              FROM alive{rounds} GROUP BY crowd_id, s_lo, s_hi HAVING count(*) >= {p.k_c}) c
            JOIN (SELECT crowd_id, list(obj_id ORDER BY obj_id) AS members FROM real{rounds} GROUP BY crowd_id) m USING (crowd_id)""",
        "windows": "SELECT DISTINCT unnest(generate_series(s_lo, s_hi)) AS win, agg_id, path, members FROM agg",
        "closed": """SELECT w.* FROM windows w WHERE NOT EXISTS (SELECT 1 FROM windows v WHERE v.win = w.win
            AND len(v.path) > len(w.path) AND list_has_all(v.path, w.path))""",
        "grp": """SELECT win, win || ':' || array_to_string(members, ',') AS group_id, members, len(members) AS size, count(*) AS n_aggs
            FROM closed GROUP BY win, members""",
        "evo": f"""SELECT a.win, a.group_id AS src_group, b.group_id AS dst_group, len(list_intersect(a.members, b.members)) AS common,
            len(list_intersect(a.members, b.members))::DOUBLE / least(a.size, b.size) AS ratio
            FROM grp a JOIN grp b ON b.win = a.win + 1
            WHERE len(list_intersect(a.members, b.members)) > 0
              AND len(list_intersect(a.members, b.members)) >= {p.m_g}::DOUBLE * least(a.size, b.size)""",
        "walks": """SELECT [group_id] AS groups, win AS first_win, group_id AS tail FROM grp
            WHERE group_id NOT IN (SELECT dst_group FROM evo)
            UNION ALL SELECT list_append(w.groups, e.dst_group), w.first_win, e.dst_group FROM walks w JOIN evo e ON e.src_group = w.tail""",
        "chain": f"""SELECT array_to_string(groups, '|') AS chain_id, first_win, first_win + len(groups) - 1 AS last_win,
            len(groups) AS n_windows, len(groups) + {p.w - 1} AS n_timestamps,
            first_win + len(groups) - 1 < (SELECT max(win) FROM grp) AS closed
            FROM walks WHERE tail NOT IN (SELECT src_group FROM evo) AND len(groups) >= {p.k_g}""",
    }
    return out


def sector_steps(p: Params, n_rings: int, per_ring: int) -> dict[str, str]:
    """Steps that read ``shape``: homes of clusters in balanced space parts, and what a later cluster reaches."""
    turn = "(2 * pi())"

    def meets(reach: str) -> str:
        wide = f"(({reach}) * (1 + 1e-9) + 1e-9)"
        half = f"((CASE WHEN {wide} >= b.rho THEN pi() ELSE asin(least({wide} / b.rho, 1)) END) + 1e-9)"
        turns = " OR ".join(
            f"(b.theta - {half} + {k} * {turn} < g.a_hi AND b.theta + {half} + {k} * {turn} >= g.a_lo)" for k in (-1, 0, 1)
        )
        return f"b.rho + {wide} >= g.r_lo AND b.rho - {wide} <= g.r_hi AND ({turns})"

    cuts = lambda keys, v, n, name: f"""SELECT {keys}, {name}, CASE WHEN {name} = 1 THEN 0.0 ELSE lo END AS lo,
        lead(lo, 1, 'inf'::DOUBLE) OVER (PARTITION BY {keys} ORDER BY {name}) AS hi FROM (
          SELECT {keys}, {name}, min({v})::DOUBLE AS lo FROM (SELECT *, ntile({n}) OVER (PARTITION BY {keys} ORDER BY {v}, cluster_id) AS {name} FROM src)
          GROUP BY {keys}, {name})"""  # noqa: E731
    return {
        "mid": "SELECT (min(mx) + max(mx)) / 2 AS cx, (min(my) + max(my)) / 2 AS cy FROM shape",
        "polar": f"""SELECT *, CASE WHEN a < 0 THEN a + {turn} ELSE a END AS theta FROM (SELECT cluster_id, t, r,
            sqrt((mx - cx) * (mx - cx) + (my - cy) * (my - cy)) AS rho, atan2(my - cy, mx - cx) AS a FROM shape, mid)""",
        "ring": "WITH src AS (FROM polar) " + cuts("t", "rho", n_rings, "ring"),
        "ringed": "SELECT p.*, g.ring, g.lo AS r_lo, g.hi AS r_hi FROM polar p JOIN ring g ON g.t = p.t AND p.rho >= g.lo AND p.rho < g.hi",
        "sector": "WITH src AS (FROM ringed) " + cuts("t, ring", "theta", per_ring, "sector"),
        "part": f"""SELECT s.t, (s.ring - 1) * {per_ring} + s.sector - 1 AS part, g.lo AS r_lo, g.hi AS r_hi, s.lo AS a_lo, s.hi AS a_hi
            FROM sector s JOIN ring g ON g.t = s.t AND g.ring = s.ring""",
        "homes": """SELECT p.t, p.cluster_id, g.part, g.r_lo, g.r_hi, g.a_lo, g.a_hi FROM polar p JOIN part g ON g.t = p.t
            AND p.rho >= g.r_lo AND p.rho < g.r_hi AND p.theta >= g.a_lo AND p.theta < g.a_hi""",
        "reached": f"""SELECT g.cluster_id AS src, b.cluster_id AS dst, {meets(f"b.r + {p.d}::DOUBLE")} AS narrow
            FROM homes g JOIN polar b ON b.t > g.t AND b.t - g.t <= {p.max_gap} WHERE {meets(f"b.r + {p.d}::DOUBLE * (b.t - g.t)")}""",
        "met": f"SELECT b.cluster_id, b.t, g.part FROM polar b JOIN part g ON g.t = b.t - 1 AND {meets(f'b.r + {p.d}::DOUBLE')}",
    }


def strict_steps(k_c: int = 1, k_p: int = 1, m_p: int = 1) -> dict[str, str]:
    """Steps that read ``link``: maximal runs at consecutive timestamps, and their parts whose every cluster has enough participators."""
    return {
        "next": "SELECT src, dst FROM link WHERE dt = 1",
        "runs": """SELECT [cluster_id] AS path, cluster_id AS tail FROM shape s WHERE NOT EXISTS (SELECT 1 FROM next n WHERE n.dst = s.cluster_id)
            UNION ALL SELECT list_append(r.path, n.dst), n.dst FROM runs r JOIN next n ON n.src = r.tail""",
        "strict": """SELECT array_to_string(path, '-') AS crowd_id, path, len(path) AS n FROM runs r
            WHERE NOT EXISTS (SELECT 1 FROM next n WHERE n.src = r.tail)""",
        "part": f"""SELECT crowd_id, path, n, lo, hi FROM (SELECT *, unnest(generate_series(lo + {k_c - 1}, n)) AS hi FROM (
            SELECT *, unnest(generate_series(1, n)) AS lo FROM strict WHERE n >= {k_c}))""",
        "place": "SELECT crowd_id, lo, hi, unnest(path[lo:hi]) AS cluster_id FROM part",
        "often": f"""SELECT p.crowd_id, p.lo, p.hi, m.obj_id FROM place p JOIN member m USING (cluster_id)
            GROUP BY ALL HAVING count(*) >= {k_p}""",
        "gathering": f"""SELECT crowd_id, path, n, lo, hi FROM part JOIN (
            SELECT crowd_id, lo, hi FROM (SELECT p.crowd_id, p.lo, p.hi, p.cluster_id, count(o.obj_id) AS c FROM place p JOIN member m USING (cluster_id)
              LEFT JOIN often o ON o.crowd_id = p.crowd_id AND o.lo = p.lo AND o.hi = p.hi AND o.obj_id = m.obj_id GROUP BY ALL)
            GROUP BY ALL HAVING min(c) >= {m_p}) USING (crowd_id, lo, hi)""",
    }


def recall_sql(p: Params, walks: str, district: int) -> str:
    """Precision and recall of groups on chains of ``k_g`` windows against the planted groups."""
    return sql(
        f"""SELECT tp, fp, fn, round(CASE WHEN tp + fp > 0 THEN tp::DOUBLE / (tp + fp) END, 6) AS precision, round(CASE WHEN tp + fn > 0 THEN tp::DOUBLE / (tp + fn) END, 6) AS recall,
          round(CASE WHEN 2 * tp + fp + fn > 0 THEN 2.0::DOUBLE * tp / (2 * tp + fp + fn) END, 6) AS f1
        FROM (SELECT count(*) FILTER (WHERE f AND g) AS tp, count(*) FILTER (WHERE f AND g IS NULL) AS fp, count(*) FILTER (WHERE f IS NULL AND g) AS fn
          FROM (SELECT DISTINCT members, true AS f FROM grp JOIN ins ON ins.g = group_id JOIN outs ON outs.g = group_id GROUP BY group_id, members HAVING max(ins.n) + max(outs.n) - 1 >= {p.k_g})
          FULL JOIN (SELECT members, true AS g FROM truth) USING (members))""",
        "evo",
        p,
        {
            "ins": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.dst_group, i.n + 1 FROM ins i JOIN evo e ON e.src_group = i.g",
            "outs": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.src_group, o.n + 1 FROM outs o JOIN evo e ON e.dst_group = o.g",
            "truth": f"""SELECT list(c_custkey ORDER BY c_custkey) AS members FROM customer
              GROUP BY c_custkey // 4 HAVING (min(c_custkey) % {district} // 4) % 3 <> 2""",
        },
        snap=walks,
    )


def sql(select: str, upto: str, p: Params = Params(), more: dict[str, str] | None = None, **instead: str) -> str:
    """``select`` over the steps up to and with ``upto``, some of them replaced, and ``more`` that read them."""
    named = steps(p)
    names = list(named)[: list(named).index(upto) + 1]
    # a step that stands for another needs none of those before it
    first = max([names.index(n) for n in instead], default=0)
    chosen = {n: instead.get(n, named[n]) for n in names[first:]} | (more or {})
    return "WITH RECURSIVE " + ",\n".join(f"{n} AS ({text})" for n, text in chosen.items()) + "\n" + select
