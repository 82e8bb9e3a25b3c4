"""The selectors in plain SQL, written apart from the DataFrame code: the check of its results."""

from __future__ import annotations

from ..sources.frames import plain_sql

ORDER = "supp DESC, size, f1, v1, coalesce(f2, -1), coalesce(v2, ''), y"
EPS = "0.000001"


def _list(*parts: str) -> str:
    return ", ".join(p for p in parts if p)


def item_rows(features: list[str], by: str = "") -> str:
    return " UNION ALL ".join(f"SELECT {_list('rid', by, f'{i} AS f', f'CAST({c} AS VARCHAR) AS v', 'y')} FROM base WHERE {c} IS NOT NULL" for i, c in enumerate(features, 1))


def counted(select: str, features: list[str], by: str = "") -> str:
    """CTEs base, items, lab(y, supp_y, n, k) and sets1."""
    part = f"PARTITION BY {by}" if by else ""
    return f"""WITH base AS (SELECT row_number() OVER () AS rid, b.* FROM ({plain_sql(select)}) b WHERE y IS NOT NULL),
items AS ({item_rows(features, by)}),
lab AS (SELECT {_list(by, 'y', 'count(*) AS supp_y', f'sum(count(*)) OVER ({part}) AS n', f'count(*) OVER ({part}) AS k')} FROM base GROUP BY {_list(by, 'y')}),
sets1 AS (SELECT {_list(by, '1 AS size', 'f AS f1', 'v AS v1', 'CAST(NULL AS INT) AS f2', 'CAST(NULL AS VARCHAR) AS v2', 'y', 'count(*) AS supp')} FROM items GROUP BY {_list(by, 'f', 'v', 'y')})"""


def mined(select: str, features: list[str], d_freq: int, per_class: bool, by: str = "", shares: str = "even", least: int = 0) -> str:
    """counted() with cand, pairs, freq (the frequent sets) and scored."""
    group = _list(by, "y" if per_class else "")
    part = f"PARTITION BY {group}" if group else ""
    same = " AND ".join(f"a.{c} = b.{c}" for c in (["y"] + ([by] if by else [])))
    lab_on = " AND ".join(f"s.{c} = l.{c}" for c in (["y"] + ([by] if by else [])))
    share = {"even": f"{d_freq} // l.k", "proportional": f"floor({d_freq} * l.supp_y / l.n)"}.get(shares, shares)
    budget = f"greatest(1, {share})" if per_class else str(d_freq)
    cols = _list(by, "size", "f1", "v1", "f2", "v2", "y", "supp")
    pre = (by + ", ") if by else ""

    def cut(source: str) -> str:
        return f"SELECT * FROM (SELECT {', '.join('s.' + c.strip() for c in cols.split(','))}, row_number() OVER ({part.replace('y', 's.y') if not by else part.replace(by, 's.' + by).replace(', y', ', s.y')} ORDER BY s.supp DESC, s.size, s.f1, s.v1, coalesce(s.f2, -1), coalesce(s.v2, ''), s.y) AS rank, {budget} AS budget FROM {source} s JOIN lab l ON {lab_on} WHERE s.supp >= {least}) q WHERE rank <= budget"

    x_on = " AND ".join(["q.f1 = t.f1", "q.v1 = t.v1", "q.f2 IS NOT DISTINCT FROM t.f2", "q.v2 IS NOT DISTINCT FROM t.v2"] + ([f"q.{by} = t.{by}"] if by else []))
    l_on = " AND ".join(f"q.{c} = l.{c}" for c in (["y"] + ([by] if by else [])))
    return counted(select, features, by) + f""",
top1 AS ({cut('sets1')}),
cand AS (SELECT {pre.replace(by, 'a.' + by) if by else ''}a.f1, a.v1, b.f1 AS f2, b.v1 AS v2, a.y FROM top1 a JOIN top1 b ON {same} AND a.f1 < b.f1),
few AS (SELECT i.* FROM items i SEMI JOIN (SELECT DISTINCT {pre}f1 AS f, v1 AS v FROM top1) k USING ({pre}f, v)),
two AS (SELECT {('a.' + by + ', ') if by else ''}a.f AS f1, a.v AS v1, b.f AS f2, b.v AS v2, a.y, count(*) AS supp FROM few a JOIN few b ON a.rid = b.rid AND a.f < b.f GROUP BY ALL),
sets2 AS (SELECT {_list(by, '2 AS size', 'f1', 'v1', 'f2', 'v2', 'y', 'supp')} FROM two SEMI JOIN cand USING ({pre}f1, v1, f2, v2, y)),
every AS (SELECT {cols} FROM sets1 UNION ALL SELECT {cols} FROM sets2),
freq AS ({cut('every')}),
tot AS (SELECT {_list(by, 'f1', 'v1', 'f2', 'v2', 'sum(supp) AS supp_x')} FROM (SELECT {cols} FROM sets1 UNION ALL SELECT {_list(by, '2 AS size', 'f1', 'v1', 'f2', 'v2', 'y', 'supp')} FROM two) z GROUP BY {_list(by, 'f1', 'v1', 'f2', 'v2')}),
scored AS (SELECT q.*, t.supp_x, l.supp_y, l.n, CAST(q.supp AS DOUBLE) / CAST(t.supp_x AS DOUBLE) AS conf,
  (CAST(q.supp AS DOUBLE) * CAST(l.n AS DOUBLE)) / (CAST(t.supp_x AS DOUBLE) * CAST(l.supp_y AS DOUBLE)) AS lift,
  CAST(q.supp AS DOUBLE) / (CAST(t.supp_x AS DOUBLE) - CAST(q.supp AS DOUBLE) + CAST({EPS} AS DOUBLE)) * ((CAST(l.n AS DOUBLE) - CAST(l.supp_y AS DOUBLE)) / CAST(l.supp_y AS DOUBLE)) AS rconf
  FROM freq q JOIN tot t ON {x_on} JOIN lab l ON {l_on})"""


def beaten(score: str = "rconf", redundancy: str = "strict", margin: float = 1.0, by: str = "") -> str:
    """CTE kept: scored without redundant pairs; CTE lost: those pairs."""
    sign = ">" if redundancy == "strict" else ">="
    on = " AND ".join(f"s.{c} = {{m}}.{c}" for c in (["y"] + ([by] if by else [])))
    return f""",
bar AS (SELECT s.*, greatest(m1.{score}, m2.{score}) * CAST({margin} AS DOUBLE) AS bar FROM scored s
  LEFT JOIN scored m1 ON m1.size = 1 AND s.size = 2 AND s.f1 = m1.f1 AND s.v1 = m1.v1 AND {on.format(m='m1')}
  LEFT JOIN scored m2 ON m2.size = 1 AND s.size = 2 AND s.f2 = m2.f1 AND s.v2 = m2.v1 AND {on.format(m='m2')}),
kept AS (SELECT * EXCLUDE (bar) FROM bar WHERE size = 1 OR bar IS NULL OR {score} {sign} bar),
lost AS (SELECT * EXCLUDE (bar) FROM bar WHERE size = 2 AND NOT ({score} {sign} bar))"""


def ranked(source: str, score: str, d_conf: int, by: str = "") -> str:
    part = f"PARTITION BY {by}" if by else ""
    return f"SELECT * FROM (SELECT * EXCLUDE (rank), row_number() OVER ({part} ORDER BY {score} DESC, {ORDER}) AS rank FROM {source}) z WHERE rank <= {d_conf}"


SETS_OUT = "size, f1, v1, coalesce(f2, 0) AS f2, coalesce(v2, '') AS v2, y, supp, CAST(rank AS BIGINT) AS rank"
RULES_OUT = "size, f1, v1, coalesce(f2, 0) AS f2, coalesce(v2, '') AS v2, y, supp, CAST(supp_x AS BIGINT) AS supp_x, round(conf, 6) AS conf, round(lift, 6) AS lift, round(ln(rconf), 6) AS log_rconf, CAST(rank AS BIGINT) AS rank"
FEATURES_OUT = "CAST(row_number() OVER (ORDER BY size, f1, v1, coalesce(f2, -1), coalesce(v2, '')) AS BIGINT) AS feature_id, size, f1, v1, f2, v2"


def rules_sql(select, features, d_freq, d_conf, per_class=True, score="rconf", redundancy=None, margin=1.0) -> str:
    text = mined(select, features, d_freq, per_class)
    if redundancy:
        text += beaten(score, redundancy, margin)
    return f"{text} SELECT {RULES_OUT} FROM ({ranked('kept' if redundancy else 'scored', score, d_conf)}) r"


def features_cte(select, features, d_freq, d_conf, per_class=True, score="rconf", redundancy=None, margin=1.0) -> str:
    """The chain with a last CTE feats."""
    text = mined(select, features, d_freq, per_class)
    if redundancy:
        text += beaten(score, redundancy, margin)
    return f"{text}, feats AS (SELECT {FEATURES_OUT} FROM (SELECT DISTINCT size, f1, v1, f2, v2 FROM ({ranked('kept' if redundancy else 'scored', score, d_conf)}) r) d)"


def held_cte(features: list[str]) -> str:
    """held(rid, feature_id): records with all of a feature's values."""
    return """, held AS (SELECT a.rid, g.feature_id FROM feats g JOIN items a ON a.f = g.f1 AND a.v = g.v1 LEFT JOIN items b ON b.rid = a.rid AND b.f = g.f2 AND b.v = g.v2 WHERE g.f2 IS NULL OR b.rid IS NOT NULL)"""
