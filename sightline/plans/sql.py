"""The scenes as SQL for DuckDB, written apart from the column expressions."""

from __future__ import annotations


def noise(salt: int, obj: str = "obj", t: str = "t") -> str:
    return f"(((({obj})::BIGINT * 1000003 + ({t})::BIGINT * 7919 + {salt * 104729}) % 1000003) % 1000)"


_P = [((0, 192), (320, 192), (640, 192)), ((640, 240), (320, 240), (0, 240)), ((280, 0), (280, 192), (280, 384)), ((360, 384), (360, 212), (640, 212)), ((0, 160), (300, 160), (300, 0))]


def _curve(axis: int) -> str:
    rows = " ".join(
        f"WHEN {k} THEN (1e0 - u) * (1e0 - u) * {a[axis]}e0 + 2e0 * u * (1e0 - u) * {b[axis]}e0 + u * u * {c[axis]}e0" for k, (a, b, c) in enumerate(_P)
    )
    return f"CASE pat {rows} END + lane"


SCENE = f"""raw AS (
    SELECT o.*, c.*, n.*, round(o_totalprice * 100e0)::BIGINT AS cents,
        CASE c_mktsegment WHEN 'MACHINERY' THEN 'bus' WHEN 'BUILDING' THEN 'walker' ELSE 'car' END AS category
    FROM orders o JOIN customer c ON o_custkey = c_custkey JOIN nation n ON c_nationkey = n_nationkey
    WHERE o_orderkey % (2 * (1 + n_regionkey)) = 0
), obj AS (
    SELECT n_regionkey::INT AS scene, o_orderkey // 250 AS clip, o_orderkey AS obj, (n_nationkey // 5)::INT AS pat, category,
        CASE category WHEN 'bus' THEN 96e0 WHEN 'car' THEN 64e0 ELSE 32e0 END AS w, CASE category WHEN 'bus' THEN 64e0 WHEN 'car' THEN 40e0 ELSE 48e0 END AS h,
        cents % 480 AS t_in, (32 + (cents // 480) % 97) * CASE category WHEN 'walker' THEN 2 ELSE 1 END AS dur,
        o_orderstatus = 'P' AS braking, (c_custkey % 5 - 2) * 6e0 AS lane, o_custkey % 12 AS vec_id FROM raw
), step AS (
    SELECT *, t_in + k AS t, k::DOUBLE / dur::DOUBLE AS v FROM (SELECT *, unnest(range(0, least(dur, 479 - t_in) + 1)) AS k FROM obj)
), moved AS (SELECT *, CASE WHEN braking THEN v * (2e0 - v) ELSE v END AS u FROM step),
det AS (SELECT scene, clip, t, obj, category, {_curve(0)} AS x, {_curve(1)} AS y, w, h, k, dur, pat, vec_id FROM moved)"""

CELLS = """cells AS (
    SELECT DISTINCT scene, clip, t, cx::INT AS cx, unnest(range(floor(greatest(y - h / 2e0, 0e0) / 32e0)::BIGINT, ceil(least(y + h / 2e0, 384e0) / 32e0)::BIGINT))::INT AS cy
    FROM (SELECT *, unnest(range(floor(greatest(x - w / 2e0, 0e0) / 32e0)::BIGINT, ceil(least(x + w / 2e0, 640e0) / 32e0)::BIGINT)) AS cx FROM det
        WHERE x + w / 2e0 > 0e0 AND x - w / 2e0 < 640e0 AND y + h / 2e0 > 0e0 AND y - h / 2e0 < 384e0)
)"""

SIM = f"""sim AS (
    SELECT scene, clip, t, obj, category, x + ({noise(29)} / 500e0 - 1e0) * 1.5625e0 AS x, y + ({noise(31)} / 500e0 - 1e0) * 1.5625e0 AS y, w, h, 1e0 - {noise(23)} / 2000e0 AS score FROM det
    WHERE {noise(17)} >= 80e0 * CASE category WHEN 'walker' THEN 1.5e0 ELSE 1e0 END AND NOT (obj % 11 = 0 AND k >= dur // 2 AND k < dur // 2 + 6)
    UNION ALL
    SELECT scene, clip, t, -1 - t, 'car', 16e0 + 32e0 * ({noise(43, 'clip * 5 + scene')} % 20), 16e0 + 32e0 * ({noise(47, 'clip * 5 + scene')} % 12), 64e0, 40e0, 0.6e0
    FROM (SELECT DISTINCT scene, clip, t FROM det) WHERE {noise(41, 'clip * 5 + scene')} < 15
)"""


def with_scene(body: str, *more: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}{', '.join([SCENE, *more])} {body}"
