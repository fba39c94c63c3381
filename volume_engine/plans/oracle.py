"""DuckDB texts of the volumes and of the pyramid, from which the oracles are put together."""

from __future__ import annotations

#: Levels and bits of a coordinate that the texts provide for; the given tables at every scale need fewer.
LEVELS = 12
KEY_BITS = 21

VOX = {
    "ribbon": "SELECT CAST(x AS BIGINT) AS x, doc_id % 64 AS y, doc_id // 64 AS z, 0 AS c, least(512, n_chars - 512 * x) AS v FROM documents, range(0, 4000) AS r(x) WHERE n_chars > 512 * x",
    "scan": """SELECT x, y, z, c, least(sum(v), 65535) AS v FROM (
        SELECT user_id AS x, CAST(json_extract_string(props, '$.k') AS BIGINT) AS y,
          date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 4 + hour(ts) // 6 AS z,
          CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 ELSE 2 END AS c, CAST(floor(value * 100) AS BIGINT) AS v
        FROM events WHERE event_type IN ('view', 'click', 'purchase')) AS e GROUP BY x, y, z, c""",
    "sales": """SELECT x, y, z, c, CAST(CASE c WHEN 0 THEN c0 WHEN 1 THEN c1 ELSE c2 END AS BIGINT) AS v FROM (
        SELECT l_partkey * 64 // (SELECT max(p_partkey) + 1 FROM part) AS x, l_suppkey * 64 // (SELECT max(l_suppkey) + 1 FROM lineitem) AS y,
          date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) * 64 // 2520 AS z,
          max(l_quantity) * 1310 AS c0, least(floor(max(l_extendedprice)), 65535) AS c1, least(sum(CAST(round(l_discount * 100) AS BIGINT)) * 1000, 65535) AS c2
        FROM lineitem GROUP BY 1, 2, 3) AS g, range(0, 3) AS ch(c)""",
    "vec": "SELECT i % 8 AS x, i // 8 AS y, vec_id AS z, 0 AS c, CAST(floor((CAST(embedding[i + 1] AS DOUBLE) + 1) * 1000) AS BIGINT) AS v FROM embeddings, range(0, 64) AS r(i)",
    "conversations": "SELECT conv_id AS x, turn AS y, 0 AS z, CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS c, length(text) AS v FROM conversations",
    "labels": "SELECT doc_id AS x, 0 AS y, 0 AS z, c, CASE c WHEN 0 THEN quality ELSE toxic END + 1 AS v FROM labels, range(0, 2) AS ch(c)",
    "benchmark": "SELECT item_id AS x, 0 AS y, 0 AS z, 0 AS c, length(text) AS v FROM benchmark",
}
BRICK = {"ribbon": (4, 4, 4), "scan": (8, 8, 8), "sales": (8, 8, 8), "vec": (4, 4, 16), "conversations": (32, 8, 2), "labels": (16, 2, 2), "benchmark": (4, 2, 2)}


def spread(col: str, axis: int, bits: int = KEY_BITS) -> str:
    return " + ".join(f"((({col}) >> {i}) & 1) * {1 << (3 * i + axis)}::BIGINT" for i in range(bits))


def morton(x: str, y: str, z: str) -> str:
    return f"CAST({spread(x, 0)} + {spread(y, 1)} + {spread(z, 2)} AS BIGINT)"


def voxels(name: str, where: str = "", value: str = "v") -> str:
    """``vox``, ``dims`` and ``meta`` of a volume; ``where`` and ``value`` leave voxels out or change them, the grid stays."""
    dims = "SELECT 64 AS dx, 64 AS dy, 64 AS dz" if name == "sales" else "SELECT max(x) + 1 AS dx, max(y) + 1 AS dy, max(z) + 1 AS dz FROM allvox"
    mx, my, mz = BRICK[name]
    return f"""allvox AS (SELECT CAST(x AS BIGINT) AS x, CAST(y AS BIGINT) AS y, CAST(z AS BIGINT) AS z, CAST(c AS BIGINT) AS c, CAST(v AS BIGINT) AS v FROM ({VOX[name]}) AS q),
    vox AS (SELECT x, y, z, c, CAST({value} AS BIGINT) AS v FROM allvox{' WHERE ' + where if where else ''}),
    dims AS ({dims}),
    meta AS (SELECT dx, dy, dz, (SELECT min(l) FROM range(0, 20) AS t(l) WHERE {mx} << l >= dx AND {my} << l >= dy AND {mz} << l >= dz) AS top FROM dims)"""


def at(dim: str, level: int) -> str:
    return f"(({dim} + {(1 << level) - 1}) // {1 << level})"


def mipmap(name: str, *changes: str) -> str:
    parts = [voxels(name, *changes), "m0 AS (SELECT * FROM vox)"]
    for l in range(LEVELS):
        n = " * ".join(f"(least(2 * {a} + 2, {at('d' + a, l)}) - 2 * {a})" for a in "xyz")
        parts.append(f"m{l + 1} AS (SELECT x, y, z, c, s // ({n}) AS v FROM (SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, c, sum(v)::BIGINT AS s FROM m{l} GROUP BY 1, 2, 3, 4) AS g, dims)")
    union = " UNION ALL ".join(f"SELECT {l} AS level, x, y, z, c, v FROM m{l}" for l in range(LEVELS + 1))
    parts.append(f"mip AS (SELECT u.* FROM ({union}) AS u, meta WHERE level <= top)")
    return ", ".join(parts)


def bricks(name: str, *changes: str) -> str:
    m = BRICK[name]
    parts = [mipmap(name, *changes)]
    for l in range(LEVELS + 1):
        n = " * ".join(f"(least({k} * i{a} + {k}, {at('d' + a, l)}) - {k} * i{a})" for a, k in zip("xyz", m, strict=True))
        keys = ", ".join(f"{a} // {k} AS i{a}" for a, k in zip("xyz", m, strict=True))
        parts.append(
            f"""b{l} AS (SELECT {l} AS level, ix, iy, iz, c, n, CASE WHEN cnt < n THEN least(lo, 0) ELSE lo END AS bmin, CASE WHEN cnt < n THEN greatest(hi, 0) ELSE hi END AS bmax, s AS bsum, s // n AS avg
            FROM (SELECT g.*, {n} AS n FROM (SELECT {keys}, c, min(v) AS lo, max(v) AS hi, sum(v)::BIGINT AS s, count(*) AS cnt FROM m{l} GROUP BY 1, 2, 3, 4) AS g, dims) AS h)"""
        )
        if l == 0:
            parts.append("s0 AS (SELECT *, bmin AS smin, bmax AS smax FROM b0)")
            continue
        kids = " * ".join(f"(least(2 * i{a} + 2, ({at('d' + a, l - 1)} + {k - 1}) // {k}) - 2 * i{a})" for a, k in zip("xyz", m, strict=True))
        parts.append(
            f"""s{l} AS (SELECT b.*, CASE WHEN kids < want THEN least(bmin, kmin, 0) ELSE least(bmin, kmin) END AS smin, CASE WHEN kids < want THEN greatest(bmax, kmax, 0) ELSE greatest(bmax, kmax) END AS smax
            FROM b{l} AS b JOIN (SELECT g.*, {kids} AS want FROM (SELECT ix // 2 AS ix, iy // 2 AS iy, iz // 2 AS iz, c, min(smin) AS kmin, max(smax) AS kmax, count(*) AS kids FROM s{l - 1} GROUP BY 1, 2, 3, 4) AS g, dims) AS k USING (ix, iy, iz, c))"""
        )
    cols = "level, ix, iy, iz, c, n, bmin, bmax, bsum, avg, smin, smax"
    union = " UNION ALL ".join(f"SELECT {cols} FROM s{l}" for l in range(LEVELS + 1))
    parts.append(f"stats AS (SELECT u.* FROM ({union}) AS u, meta WHERE level <= top)")
    return ", ".join(parts)


def nodes(name: str, threshold: float, channels: int, *changes: str) -> str:
    avgs = ", ".join(f"coalesce(max(CASE WHEN c = {c} THEN avg END), 0) AS avg{c}" for c in range(channels))
    return (
        bricks(name, *changes)
        + f""", nodes AS (SELECT *, {morton('ix', 'iy', 'iz')} AS key, CAST(spread < {threshold} AS INT) AS homog, CAST(subspread < {threshold} AS INT) AS subhomog
        FROM (SELECT level, ix, iy, iz, max(bmax - bmin) AS spread, max(smax - smin) AS subspread, max(n) AS n, {avgs} FROM stats GROUP BY 1, 2, 3, 4) AS g),
        kept AS (SELECT a.* FROM nodes AS a WHERE NOT EXISTS (SELECT 1 FROM nodes AS p WHERE p.subhomog = 1 AND p.level = a.level + 1 AND p.key = a.key >> 3))"""
    )


SAMPLE = 16


def rays(name: str, w: int = SAMPLE, h: int = SAMPLE) -> str:
    return f"""{voxels(name)}, ray AS (SELECT px, py, (2 * px + 1) * dx // {2 * w} AS x, (2 * py + 1) * dy // {2 * h} AS y, 0 AS t0, dz AS t1 FROM range(0, {w}) AS a(px), range(0, {h}) AS b(py), dims),
    hit AS (SELECT px, py, vox.z AS i, c, v FROM ray JOIN vox USING (x, y))"""


def shade(hi: int) -> str:
    return f"shaded AS (SELECT *, v * (0.5 / {hi}) AS a, CAST(c = 0 AS INT) * 1.0 AS r, CAST(c = 1 AS INT) * 1.0 AS g, CAST(c = 2 AS INT) * 1.0 AS b FROM hit)"


def dvr(stop: float | None = None) -> str:
    where = f"WHERE 1 - t < {stop}" if stop else ""
    return f"""front AS (SELECT *, exp(coalesce(sum(ln(1 - a)) OVER (PARTITION BY px, py ORDER BY i, c ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS t FROM shaded)
    SELECT px, py, round(sum(t * a * r), 6) AS r, round(sum(t * a * g), 6) AS g, round(sum(t * a * b), 6) AS b, round(sum(t * a), 6) AS a, count(*) AS samples FROM front {where} GROUP BY px, py"""
