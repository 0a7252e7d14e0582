"""Shared DuckDB text: the grid edge, the density field and what is derived from it."""

G = "g AS (SELECT CASE WHEN count(*) < 5000 THEN 16 WHEN count(*) < 50000 THEN 32 ELSE 64 END AS g FROM events)"
ZEROS = "zeros AS (SELECT x, y, z FROM g, unnest(range(g)) AS a(x), unnest(range(g)) AS b(y), unnest(range(g)) AS c(z))"

HALO = f"""{G}, {ZEROS},
heavy AS (SELECT event_id, CAST(floor(value * 100 + 0.5) AS BIGINT) AS m FROM events ORDER BY m DESC, event_id LIMIT 400),
hashed AS (SELECT (event_id * 2654435761) % 4294967296 AS h, m FROM heavy),
masses AS (SELECT (h // 256) % g AS cx, (h // 65536) % g AS cy, (h // 16777216) % g AS cz, m FROM hashed, g),
kernel AS (SELECT dx, dy, dz, w * w AS w FROM (
  SELECT dx, dy, dz, (g // 6) * (g // 6) - dx * dx - dy * dy - dz * dz AS w
  FROM g, unnest(range(-(g // 6), g // 6 + 1)) AS a(dx), unnest(range(-(g // 6), g // 6 + 1)) AS b(dy), unnest(range(-(g // 6), g // 6 + 1)) AS c(dz)) WHERE w > 0),
halo AS (SELECT CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(z AS INTEGER) AS z, CAST(sum(v) AS BIGINT) AS v FROM (
  SELECT (cx + dx + g) % g AS x, (cy + dy + g) % g AS y, (cz + dz + g) % g AS z, m * w AS v FROM masses, kernel, g
  UNION ALL SELECT x, y, z, 0 FROM zeros) GROUP BY ALL)"""

#: Cubes of side 8 of the density field with their ranges.
RANGES = """rng AS (SELECT CAST((x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS BIGINT) AS key, min(v) AS lo, max(v) AS hi,
  CAST(sum(v) AS BIGINT) AS total, count(*) AS n FROM halo, g GROUP BY ALL),
ranked AS (SELECT *, hi - lo AS rng, row_number() OVER (ORDER BY hi - lo DESC, key) AS place, count(*) OVER () AS n_all FROM rng)"""

#: Prequantised values: eb is a hundredth of the range, in whole numbers.
DUAL = """lim AS (SELECT greatest(1, (max(v) - min(v)) // 100) AS eb FROM halo),
dual AS (SELECT x, y, z, v AS orig, (v + eb) // (2 * eb) AS q, (v + eb) // (2 * eb) * 2 * eb AS deco, eb FROM halo, lim)"""

#: The sample plan on cubes of side 4: one cube of 4, 3 or 2 blocks a side in the middle, as grids of up to 64 points have room for no more.
SAMPLE = """box AS (SELECT CASE WHEN cbrt(0.015 * g * g * g) >= 16 THEN 16 WHEN cbrt(0.015 * g * g * g) >= 12 THEN 12 ELSE 8 END AS side FROM g),
place AS (SELECT side, ((g - side) // 4) // 2 * 4 AS o FROM box, g),
smp AS (SELECT d.*, o FROM dual d, place WHERE x BETWEEN o AND o + side - 1 AND y BETWEEN o AND o + side - 1 AND z BETWEEN o AND o + side - 1)"""
