"""DuckDB text for the queries: common parts first, each a WITH clause's member."""

from __future__ import annotations


def days(column: str, anchor: str, width: int) -> str:
    return f"(floor(date_diff('day', DATE '{anchor}', {column}::DATE) / {width}.0) + 1)::BIGINT"


def dense(cells: str, series: str, n: int) -> str:
    return f"""cells AS ({cells}),
        grid AS (SELECT s::BIGINT AS series_id, t::BIGINT AS t FROM ({series}) AS q(s), range(1, {n + 1}) AS r(t)),
        raw AS (SELECT series_id, t, coalesce(x, 0)::DOUBLE AS x FROM grid LEFT JOIN cells USING (series_id, t))"""


NATION_WEEK = dense(
    f"""SELECT c_nationkey::BIGINT AS series_id, {days('o_orderdate', '1995-01-01', 7)} AS t, sum(o_totalprice::DECIMAL(18,4))::DOUBLE AS x
        FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL""",
    "SELECT n_nationkey FROM nation", 343,
)


def supplier_week(weeks: int = 356) -> str:
    return dense(
        f"""SELECT l_suppkey AS series_id, {days('l_shipdate', '1995-01-02', 7)} AS t, sum((l_extendedprice * (1 - l_discount))::DECIMAL(18,4))::DOUBLE AS x
            FROM lineitem GROUP BY ALL""",
        "SELECT s_suppkey FROM supplier", weeks,
    )


def event_hour(hours: int = 720) -> str:
    return f"""types AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS type_no FROM (SELECT DISTINCT event_type FROM events)),
        """ + dense(
        """SELECT (type_no * 10 + user_id % 10)::BIGINT AS series_id,
                  (floor(date_diff('second', TIMESTAMP '2024-01-01', ts) / 3600.0) + 1)::BIGINT AS t, count(*)::DOUBLE AS x
           FROM events JOIN types USING (event_type) GROUP BY ALL""",
        "SELECT type_no * 10 + b FROM types, range(10) AS r(b)", hours,
    )


EMBEDDING_STREAM = """raw AS (SELECT i::BIGINT AS series_id, (vec_id + 1)::BIGINT AS t, embedding[i]::DOUBLE AS x
        FROM embeddings, range(1, 65) AS r(i))"""


SCALE = """diffs AS (SELECT series_id, t, x - lag(x) OVER (PARTITION BY series_id ORDER BY t) AS d FROM raw),
        scales AS (SELECT series_id, avg(abs(d - m)) * sqrt(pi()) / 2 AS sigma
                   FROM (SELECT *, avg(d) OVER (PARTITION BY series_id) AS m FROM diffs WHERE d IS NOT NULL) GROUP BY series_id),
        std AS (SELECT series_id, t, coalesce(x / nullif(sigma, 0), 0) AS x FROM raw JOIN scales USING (series_id))"""


def planted(zs: tuple[int | str, ...], size: float, factors: tuple[float, ...], chosen: str) -> str:
    """The standardised panel with steps on the series that the condition chosen selects."""
    step = " + ".join(f"(t > {z})::INT * {f}" for z, f in zip(zs, factors, strict=True))
    return f"""hit AS (SELECT DISTINCT series_id FROM std WHERE {chosen}),
        panel AS (SELECT std.series_id, t, x + CASE WHEN hit.series_id IS NULL THEN 0
                         ELSE {size} / sqrt((SELECT count(*) FROM hit)) * ({step}) END AS x
                  FROM std LEFT JOIN hit USING (series_id))"""


def cusum(source: str = "panel", name: str = "cus") -> str:
    return f"""{name}_p AS (SELECT series_id, t, sum(x) OVER (PARTITION BY series_id ORDER BY t) AS pref, sum(x) OVER (PARTITION BY series_id) AS tot,
                      (max(t) OVER (PARTITION BY series_id))::DOUBLE AS n FROM {source}),
        {name} AS (SELECT series_id, t, (t * tot - n * pref) / sqrt(n * t * (n - t)) AS cusum FROM {name}_p WHERE t < n)"""


#: The practical level for disjoint blocks of ten series.
BLOCKS = "grp AS (SELECT DISTINCT series_id // 10 AS group_id, series_id FROM panel)"
LEVEL = """lev AS (SELECT (1 + sqrt(4 * ln(count(*) * (SELECT max(t) FROM panel)) / min(p_g))) / 2 AS lam
        FROM (SELECT group_id, count(*) AS p_g FROM grp GROUP BY group_id))"""


def shrunk(c: str = "cus") -> str:
    return f"""sized AS (SELECT group_id, series_id, count(*) OVER (PARTITION BY group_id) AS p_g FROM grp),
        norms AS (SELECT group_id, t, sqrt(sum(cusum * cusum)) AS norm, any_value(p_g) AS p_g FROM {c} JOIN sized USING (series_id) GROUP BY group_id, t),
        shr AS (SELECT series_id, t, cusum * (1 - lam * sqrt(p_g) / norm) AS m
                FROM {c} JOIN grp USING (series_id) JOIN norms USING (group_id, t), lev WHERE norm > lam * sqrt(p_g))"""


def direction(m: str = "shr", steps: int = 60) -> str:
    """Power steps on the Gram matrix from equal entries, with the largest entry made positive."""
    return f"""gram AS MATERIALIZED (SELECT a.series_id AS i, b.series_id AS j, sum(a.m * b.m) AS g FROM {m} a JOIN {m} b USING (t) GROUP BY ALL),
        pw(k, i, v) AS (
            SELECT 0, series_id, 1.0::DOUBLE FROM (SELECT DISTINCT series_id FROM {m})
            UNION ALL
            SELECT k + 1, i, u / sqrt(sum(u * u) OVER ())
            FROM (SELECT pw.k AS k, gram.i AS i, sum(gram.g * pw.v) AS u FROM pw JOIN gram ON gram.j = pw.i WHERE pw.k < {steps} GROUP BY pw.k, gram.i)),
        dir AS (SELECT i AS series_id, v * sign(arg_max(v, abs(v)) OVER ()) AS v FROM pw WHERE k = {steps})"""


def located(direction: str = "dir", c: str = "cus") -> str:
    return f"curve AS (SELECT t, abs(sum(v * cusum)) AS s FROM {c} JOIN {direction} USING (series_id) GROUP BY t)"


PEAK = "SELECT arg_max(t, s)::BIGINT AS z, round(max(s), 4) AS stat FROM curve"
