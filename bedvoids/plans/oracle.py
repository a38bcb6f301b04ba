"""The queries' answers in SQL, written on their own: only numbers of grids and scenes are shared."""

from __future__ import annotations

from ..functions.grid import SPANS, Box, bed_grid
from ..sources.particles import STEPS as SCENE_STEPS
from ..sources.particles import void_rows
from .scenes import BOXES, LEAST
from .workloads import BINS, ORDER_BINS, order_grid, void_box

NX, NY, NZ = 24, 6, 24
G = NX * NY * NZ
#: Width of a bin on each axis.
W = tuple((SPANS[a][1] - SPANS[a][0]) / n for a, n in zip("xyz", (NX, NY, NZ), strict=True))
FLOOR = (1 / 12) ** 0.5


def d(v: float) -> str:
    return f"CAST('{v!r}' AS DOUBLE)"


PARTICLES = f"""particles AS (
  SELECT year(l_shipdate) - 1995 AS step, l_suppkey, l_linenumber, l_extendedprice AS x,
    {d(10.0)} - abs({d(10.0)} - abs(round(l_discount * 100) - {d(0.5)} + (l_partkey % 64) / {d(64.0)})) AS y,
    l_quantity - {d(1.0)} + (l_orderkey % 64) / {d(64.0)} AS z,
    round(l_tax * 100) - {d(4.0)} AS vx, CAST(l_linenumber % 3 - 1 AS DOUBLE) AS vy
  FROM lineitem
)"""


def binned(n: tuple[int, int, int] = (NX, NY, NZ), source: str = "particles", spans: dict | None = None, extra: str = "") -> str:
    spans = spans or SPANS
    index, test = [], []
    for a, k in zip("xyz", n, strict=True):
        lo, hi = spans[a]
        index.append(f"CAST(least(floor(({a} - {d(lo)}) / {d((hi - lo) / k)}), {k - 1}) AS INT) AS i{a}")
        test.append(f"{a} BETWEEN {d(lo)} AND {d(hi)}")
    return f"SELECT *, {', '.join(index)} FROM {source} WHERE {' AND '.join(test)}{extra}"


VOXEL = f"(CAST(ix AS BIGINT) * {NY} + iy) * {NZ} + iz"
def lattice(n: tuple[int, int, int] = (NX, NY, NZ)) -> str:
    return f"lattice AS MATERIALIZED (SELECT v AS voxel, CAST(v // {n[1] * n[2]} AS INT) AS ix, CAST(v % {n[1] * n[2]} // {n[2]} AS INT) AS iy, CAST(v % {n[2]} AS INT) AS iz FROM range({n[0] * n[1] * n[2]}) r(v))"


def voxel(n: tuple[int, int, int] = (NX, NY, NZ)) -> str:
    return f"(CAST(ix AS BIGINT) * {n[1]} + iy) * {n[2]} + iz"


def void_table(scene: str, name: str = "voids") -> str:
    rows = ", ".join(f"({r[1]}, {', '.join(d(v) for v in r[2:])})" for r in void_rows(scene))
    return f"{name}(step, x0, y0, z0, rx, ry, rz, cx, cy, cz, crx, cry, crz) AS (VALUES {rows})"


def truth(scene: str, name: str = "truth", n: tuple[int, int, int] = (NX, NY, NZ)) -> str:
    def ball(c: tuple[str, str, str], r: tuple[str, str, str]) -> str:
        terms = [f"((i{a} + {d(0.5)}) / {d(float(k))} - {p}) / {q}" for a, k, p, q in zip("xyz", n, c, r, strict=True)]
        return " + ".join(f"({t}) * ({t})" for t in terms)

    return f"""{void_table(scene, name + "_voids")},
{name} AS MATERIALIZED (
  SELECT DISTINCT CAST(step AS INT) AS step, voxel, ix, iy, iz FROM lattice, {name}_voids
  WHERE (ix + {d(0.5)}) / {d(float(n[0]))} < {d(0.85)}
    AND {ball(("x0", "y0", "z0"), ("rx", "ry", "rz"))} <= 1 AND {ball(("cx", "cy", "cz"), ("crx", "cry", "crz"))} > 1
)"""


ORDERS = f"""particles AS (
  SELECT CAST(year(o_orderdate) - 1995 AS INT) AS step, CAST(floor(o_totalprice) AS BIGINT) AS l_suppkey, o_totalprice AS x, CAST(substr(o_orderpriority, 1, 1) AS DOUBLE) - 1 + (o_orderkey % 64) / {d(64.0)} AS y,
    o_custkey % 50 + (o_orderkey % 64) / {d(64.0)} AS z, CASE o_orderstatus WHEN 'F' THEN {d(1.0)} WHEN 'P' THEN {d(-1.0)} ELSE {d(0.0)} END AS vx
  FROM orders
)"""
MOTION = """motion AS MATERIALIZED (
  SELECT CAST(step AS INT) AS step, voxel, max(speed) AS v_set FROM (
    SELECT step, voxel, CASE WHEN dx >= -rx - {e} AND dx < -rx AND dz <= rz THEN {wake} WHEN dx > rx AND dx <= rx + {e} AND dz <= rz THEN {above} WHEN abs(dx) <= rx AND dz > rz AND dz <= rz + {e} THEN {side} END AS speed
    FROM (SELECT v.step, voxel, rx, rz, (ix + {half}) / {nx} - x0 AS dx, abs((iz + {half}) / {nz} - z0) AS dz FROM lattice, truth_voids v)
  ) WHERE speed IS NOT NULL GROUP BY ALL
)"""


def bed(scene: str = "rise", steps: int | None = None, n: tuple[int, int, int] = (NX, NY, NZ), source: str = PARTICLES, spans: dict | None = None, wakes: bool = False) -> str:
    """The planted bed and its field, step by step."""
    steps = steps or SCENE_STEPS[scene]
    number = voxel(n)
    motion = ",\n" + MOTION.format(e=d(0.1), wake=d(3.0), above=d(1.0), side=d(-2.0), half=d(0.5), nx=d(float(n[0])), nz=d(float(n[2]))) if wakes else ""
    speed, join = ("coalesce(v_set, vx)", f" LEFT JOIN motion m ON m.step = t AND m.voxel = {number}".replace("ix", "p.ix").replace("iy", "p.iy").replace("iz", "p.iz")) if wakes else ("vx", "")
    own = number.replace("ix", "p.ix").replace("iy", "p.iy").replace("iz", "p.iz")
    return f"""{source}, {lattice(n)}, {truth(scene, n=n)}{motion},
placed AS ({binned(n, spans=spans)}),
bed AS (
  SELECT CAST(t AS INT) AS step, {own} AS voxel, p.ix, p.iy, p.iz, {speed} AS vx
  FROM placed p CROSS JOIN range({steps}) s(t){join}
  WHERE (p.ix + {d(0.5)}) / {d(float(n[0]))} < {d(0.85)}
    AND (l_suppkey % 8 = 0 OR NOT EXISTS (SELECT 1 FROM truth q WHERE q.step = t AND q.voxel = {own}))
),
counted AS (SELECT step, voxel, count(*) AS n, sum(vx) AS s FROM bed GROUP BY ALL),
field AS MATERIALIZED (
  SELECT CAST(t AS INT) AS step, l.voxel, l.ix, l.iy, l.iz, CAST(coalesce(n, 0) AS BIGINT) AS density, s / n AS rise_velocity
  FROM range({steps}) r(t) CROSS JOIN lattice l LEFT JOIN counted c ON c.step = t AND c.voxel = l.voxel
)"""


def block(n: tuple[int, int, int] = (NX, NY, NZ), size: int = 3) -> str:
    return f"CAST((ix // {size} * {-(-n[1] // size)} + iy // {size}) * {-(-n[2] // size)} + iz // {size} AS INT)"


def partition(t: str = "", n: tuple[int, int, int] = (NX, NY, NZ), size: int = 3) -> str:
    return f"labels{t} AS MATERIALIZED (SELECT step, voxel, {block(n, size)} AS cluster, density FROM field)"


def gaussians(t: str = "") -> str:
    return f"""gauss{t} AS MATERIALIZED (
  SELECT step, cluster, CAST(sum(density) AS DOUBLE) / count(*) AS mu, count(*) AS n,
    greatest(sqrt(CAST(sum(density * density) * count(*) - sum(density) * sum(density) AS DOUBLE) / (count(*) * count(*))), {d(FLOOR)}) AS sigma
  FROM labels{t} GROUP BY step, cluster
)"""


def target(box: Box) -> str:
    inside = " AND ".join(f"i{a} BETWEEN {lo} AND {hi}" for a, (lo, hi) in zip("xyz", (box.ix, box.iy, box.iz), strict=True))
    return f"""goal AS MATERIALIZED (
  SELECT CAST(sum(density) AS DOUBLE) / count(*) AS m0, count(*) AS n0,
    greatest(sqrt(CAST(sum(density * density) * count(*) - sum(density) * sum(density) AS DOUBLE) / (count(*) * count(*))), {d(FLOOR)}) AS s0
  FROM field WHERE step = 0 AND {inside}
)"""


def distance(spread: str = "std", digits: int = 9, t: str = "") -> str:
    a, b = ("sigma", "s0") if spread == "std" else ("(sigma * sigma)", "(s0 * s0)")
    half = f"(({a} + {b}) / {d(2.0)})"
    return f"dist{t} AS MATERIALIZED (SELECT step, cluster, round((mu - m0) * (mu - m0) / {half} / {d(8.0)} + {d(0.5)} * ln({half} / sqrt({a} * {b})), {digits}) AS distance FROM gauss{t} CROSS JOIN goal)"


def bsf(norm: str = "max", scope: str = "step", t: str = "") -> str:
    over = "OVER (PARTITION BY step)" if scope == "step" else "OVER ()"
    score = {
        "max": f"CASE WHEN max(distance) {over} > 0 THEN {d(1.0)} - distance / max(distance) {over} ELSE {d(1.0)} END",
        "minmax": f"CASE WHEN max(distance) {over} > min(distance) {over} THEN {d(1.0)} - (distance - min(distance) {over}) / (max(distance) {over} - min(distance) {over}) ELSE {d(1.0)} END",
        "coefficient": "exp(-distance)",
    }[norm]
    return f"""scored{t} AS (SELECT step, cluster, {score} AS s FROM dist{t}),
bsf{t} AS MATERIALIZED (SELECT l.step, l.voxel, s AS similarity FROM labels{t} l JOIN scored{t} USING (step, cluster))"""


def iteration(k: int, t: str = "", size: int = 3, gamma: float = 0.3, cells: bool = False) -> str:
    """A round of clustering: labels of round k and its centres from those of the round before."""
    px = " + ".join(f"(i{a} - c{a}) * (i{a} - c{a})" for a in "xyz")
    near = " AND ".join(f"abs(i{a} - c{a}) <= {size}" for a in "xyz")
    reach, same = f"centres{t}_{k - 1}", ""
    if cells:  # centres meet the voxels of the cells that they reach
        reach = f"(SELECT c.*, {', '.join(f'k{a}' for a in 'xyz')} FROM centres{t}_{k - 1} c, {', '.join(f'range(CAST(floor((c{a} - {size}) / {size}) AS BIGINT), CAST(floor((c{a} + {size}) / {size}) AS BIGINT) + 1) r{a}(k{a})' for a in 'xyz')})"
        same = " AND " + " AND ".join(f"i{a} // {size} = k{a}" for a in "xyz")
    return f"""labels{t}_{k} AS MATERIALIZED (
  SELECT b.step, b.voxel, coalesce(z.cluster, b.cluster) AS cluster, coalesce(z.cluster, b.cluster) <> b.cluster AS moved, coalesce(z.tested, 0) AS tested FROM labels{t}_{k - 1} b LEFT JOIN (
    SELECT f.step, f.voxel, arg_min(c.cluster, row({d(gamma)} * sqrt({px}) + {d(1 - gamma)} * abs(density - cv), c.cluster)) AS cluster, count(*) AS tested
    FROM field f JOIN {reach} c ON f.step = c.step{same} AND {near} GROUP BY ALL
  ) z ON z.step = b.step AND z.voxel = b.voxel
),
centres{t}_{k} AS MATERIALIZED (
  SELECT c.step, c.cluster, {", ".join(f"coalesce(m.m{a}, c.c{a}) AS c{a}" for a in "xyz")}, coalesce(m.mv, c.cv) AS cv
  FROM centres{t}_{k - 1} c LEFT JOIN (SELECT l.step, l.cluster, {", ".join(f"CAST(sum(i{a}) AS DOUBLE) / count(*) AS m{a}" for a in "xyz")}, CAST(sum(density) AS DOUBLE) / count(*) AS mv FROM labels{t}_{k} l JOIN field USING (step, voxel) GROUP BY ALL) m USING (step, cluster)
)"""


def seeds(t: str = "", n: tuple[int, int, int] = (NX, NY, NZ), size: int = 3) -> str:
    return f"""labels{t}_0 AS MATERIALIZED (SELECT step, voxel, {block(n, size)} AS cluster FROM field),
means{t} AS (SELECT step, cluster, {", ".join(f"CAST(sum(i{a}) AS DOUBLE) / count(*) AS c{a}" for a in "xyz")} FROM labels{t}_0 JOIN field USING (step, voxel) GROUP BY ALL),
centres{t}_0 AS MATERIALIZED (
  SELECT step, cluster, cx, cy, cz, CAST(arg_min(density, row((ix - cx) * (ix - cx) + (iy - cy) * (iy - cy) + (iz - cz) * (iz - cz), voxel)) AS DOUBLE) AS cv
  FROM labels{t}_0 JOIN field USING (step, voxel) JOIN means{t} USING (step, cluster) GROUP BY step, cluster, cx, cy, cz
)"""


def clustered(t: str = "", n: tuple[int, int, int] = (NX, NY, NZ), size: int = 3, gamma: float = 0.3, rounds: int = 20, cells: bool = False) -> str:
    """Supervoxels after at most 20 rounds: a step that has converged stays as it is in the rounds after."""
    chain = ", ".join(iteration(k, t, size, gamma, cells) for k in range(1, rounds + 1))
    return f"{seeds(t, n, size)}, {chain}, labels{t} AS MATERIALIZED (SELECT step, voxel, cluster, density FROM labels{t}_{rounds} JOIN field USING (step, voxel))"


def reached(source: str, name: str, connectivity: int = 6, key: str = "step", t: str = "") -> str:
    """Components of the voxels of a table: every voxel takes the smallest voxel that its neighbours know, until none changes."""
    most = {6: 1, 18: 2, 26: 3}[connectivity]
    return f"""touch{t} AS MATERIALIZED (
  SELECT a.{key}, a.voxel AS p, b.voxel AS q FROM {source} a JOIN {source} b ON a.{key} = b.{key} AND b.ix BETWEEN a.ix - 1 AND a.ix + 1 AND b.iy BETWEEN a.iy - 1 AND a.iy + 1 AND b.iz BETWEEN a.iz - 1 AND a.iz + 1
  WHERE abs(a.ix - b.ix) + abs(a.iy - b.iy) + abs(a.iz - b.iz) BETWEEN 1 AND {most}
),
spread{t}({key}, voxel, root) USING KEY ({key}, voxel) AS (
  SELECT {key}, voxel, voxel FROM {source}
  UNION
  SELECT c.{key}, c.voxel, min(x.root) FROM spread{t} x JOIN touch{t} ON touch{t}.{key} = x.{key} AND touch{t}.q = x.voxel JOIN recurring.spread{t} c ON c.{key} = touch{t}.{key} AND c.voxel = touch{t}.p
  WHERE x.root < c.root GROUP BY c.{key}, c.voxel
),
{name} AS MATERIALIZED (SELECT r.{key}, r.voxel, ix, iy, iz, CAST(dense_rank() OVER (PARTITION BY r.{key} ORDER BY root) AS INT) AS bubble FROM spread{t} r JOIN lattice USING (voxel))"""


def kept(found: str = "found", name: str = "bubbles", least: int = LEAST, n: tuple[int, int, int] = (NX, NY, NZ), key: str = "step") -> str:
    """Without the freeboard and the tiniest."""
    return f"{name} AS MATERIALIZED (SELECT f.* FROM {found} f JOIN (SELECT {key}, bubble FROM {found} GROUP BY ALL HAVING count(*) >= {least} AND max(ix) < {n[0] - 1}) USING ({key}, bubble))"


def segments(threshold: float = 0.92, t: str = "") -> str:
    return f"seg{t} AS MATERIALIZED (SELECT step, voxel, ix, iy, iz FROM bsf{t} JOIN lattice USING (voxel) WHERE similarity >= {d(threshold)})"


def run(scene: str = "rise", n: tuple[int, int, int] = (NX, NY, NZ), steps: int | None = None, box: Box | None = None, size: int = 3, cells: bool = False) -> str:
    """The similarity of supervoxels to the selected region, at all steps."""
    return f"{bed(scene, steps, n)}, {target(box or BOXES[scene])}, {clustered(n=n, size=size, cells=cells)}, {gaussians()}, {distance()}, {bsf()}"


def extracted(scene: str = "rise", connectivity: int = 6) -> str:
    return f"{run(scene)}, {segments()}, {reached('seg', 'found', connectivity)}, {kept()}"


LATTICE = lattice()
BED = bed()
ON_BLOCKS = f"WITH {BED}, {partition()}, {gaussians()}, {target(BOXES['rise'])}"
BLOCK_BSF = f"{ON_BLOCKS}, {distance()}, {bsf()}"
RUN = f"WITH {run()}"
LABELS = f"WITH RECURSIVE {extracted()}"
SHAPES = f"WITH RECURSIVE {extracted('shapes')}"
TRAITS = f"""traits AS MATERIALIZED (
  SELECT step, bubble, count(*) AS voxels,
    {", ".join(f"{d(SPANS[a][0])} + (CAST(sum(i{a}) AS DOUBLE) / count(*) + {d(0.5)}) * {d(W[i])} AS {a}c" for i, a in enumerate("xyz"))},
    {", ".join(f"min(i{a}) AS i{a}_min, max(i{a}) AS i{a}_max, var_pop(i{a}) AS v{a}" for a in "xyz")}
  FROM bubbles GROUP BY step, bubble
),
described AS (SELECT *, voxels * {d(W[0] * W[1] * W[2])} AS volume, CAST(iz_max - iz_min + 1 AS DOUBLE) / (ix_max - ix_min + 1) AS aspect, ix_max = {NX - 1} AS is_freeboard FROM traits)"""


def edges(gap: int = 1, name: str = "edges", bubbles: str = "bubbles") -> str:
    return f"""{name} AS MATERIALIZED (
  SELECT CAST(s.step AS INT) AS step, src, dst, inter, size_a, size_b,
    {d(2.0)} * inter / (size_a + size_b) AS dice, CAST(inter AS DOUBLE) / (size_a + size_b - inter) AS jaccard, CAST(inter AS DOUBLE) / least(size_a, size_b) AS overlap
  FROM (SELECT a.step, a.bubble AS src, b.bubble AS dst, count(*) AS inter FROM {bubbles} a JOIN {bubbles} b ON b.step = a.step + {gap} AND a.voxel = b.voxel GROUP BY ALL) s
  JOIN (SELECT step, bubble, count(*) AS size_a FROM {bubbles} GROUP BY ALL) x ON x.step = s.step AND x.bubble = src
  JOIN (SELECT step, bubble, count(*) AS size_b FROM {bubbles} GROUP BY ALL) y ON y.step = s.step + {gap} AND y.bubble = dst
)"""


def best(of: str = "edges", t: str = "") -> str:
    return f"""ahead_best{t} AS MATERIALIZED (SELECT step, src, dst, inter, dice FROM (SELECT *, row_number() OVER (PARTITION BY step, src ORDER BY dice DESC, inter DESC, dst) AS r FROM {of}) WHERE r = 1),
back_best{t} AS MATERIALIZED (SELECT step, src, dst, inter, dice FROM (SELECT *, row_number() OVER (PARTITION BY step, dst ORDER BY dice DESC, inter DESC, src) AS r FROM {of}) WHERE r = 1)"""


BEST = best()


def traced(start: str, step: int = 5) -> str:
    return f"""starts AS MATERIALIZED ({start}),
ahead(track, step, bubble, dice) AS (
  SELECT CAST(bubble AS BIGINT), step, bubble, CAST(NULL AS DOUBLE) FROM starts
  UNION ALL SELECT a.track, CAST(l.step + 1 AS INT), l.dst, l.dice FROM ahead a JOIN ahead_best l ON l.step = a.step AND l.src = a.bubble
),
back(track, step, bubble, dice) AS (
  SELECT CAST(bubble AS BIGINT), step, bubble, CAST(NULL AS DOUBLE) FROM starts
  UNION ALL SELECT a.track, l.step, l.src, l.dice FROM back a JOIN back_best l ON l.step = a.step - 1 AND l.dst = a.bubble
),
tracks AS MATERIALIZED (SELECT * FROM ahead UNION ALL SELECT * FROM back WHERE step < {step})"""


def mutual_chains(t: str = "", bubbles: str = "bubbles", name: str = "chain") -> str:
    return f"""mutual{t} AS MATERIALIZED (SELECT a.step, a.src, a.dst, a.dice FROM ahead_best{t} a JOIN back_best{t} b USING (step, src, dst)),
{name}(track, step, bubble, dice) AS (
  SELECT CAST(step AS BIGINT) * 4294967296 + bubble, step, bubble, CAST(NULL AS DOUBLE) FROM (SELECT DISTINCT step, bubble FROM {bubbles}) b WHERE NOT EXISTS (SELECT 1 FROM mutual{t} m WHERE m.step + 1 = b.step AND m.dst = b.bubble)
  UNION ALL SELECT track, CAST(m.step + 1 AS INT), m.dst, m.dice FROM {name} c JOIN mutual{t} m ON m.step = c.step AND m.src = c.bubble
)"""


EDGES = f"{LABELS}, {edges()}"
#: The largest bubble of the step in the middle.
SEED = "SELECT step, bubble FROM (SELECT step, bubble, count(*) AS size FROM bubbles WHERE step = 5 GROUP BY ALL) ORDER BY size DESC, bubble LIMIT 1"
SINGLE = f"{EDGES}, {BEST}, {traced(SEED)}"
TRACED = f"{LABELS}, {TRAITS}, {edges()}, {BEST}, {traced('SELECT step, bubble FROM described WHERE step = 5')}"
FOLLOWED = f"{TRACED}, followed AS MATERIALIZED (SELECT t.*, voxels, xc, volume, aspect FROM tracks t JOIN described USING (step, bubble))"
MOVING = f"{FOLLOWED}, moved AS MATERIALIZED (SELECT *, (xc - lag(xc) OVER w) / (step - lag(step) OVER w) AS rise_velocity, round(volume / lag(volume) OVER w - {d(1.0)}, 9) AS change FROM followed WINDOW w AS (PARTITION BY track ORDER BY step))"
#: The followed bubble that began as the largest.
LARGEST = f"(SELECT bubble FROM ({SEED}))"


def around(field: str = "field", t: str = "") -> str:
    return AROUND.replace("field f", f"{field} f").replace("boxes AS", f"boxes{t} AS").replace("FROM boxes", f"FROM boxes{t}").replace("near AS", f"near{t} AS").replace("FROM near", f"FROM near{t}").replace("around AS", f"around{t} AS")


AROUND = f"""boxes AS (SELECT step, bubble, {", ".join(f"min(i{a}) AS {a}0, max(i{a}) AS {a}1" for a in "xyz")} FROM bubbles GROUP BY step, bubble),
near AS (
  SELECT b.step, bubble, f.voxel, rise_velocity, CASE WHEN iz BETWEEN z0 AND z1 AND ix < x0 THEN 'below' WHEN iz BETWEEN z0 AND z1 AND ix > x1 THEN 'above' WHEN ix BETWEEN x0 AND x1 AND NOT iz BETWEEN z0 AND z1 THEN 'side' END AS region
  FROM boxes b JOIN field f ON f.step = b.step AND ix BETWEEN x0 - 2 AND x1 + 2 AND iy BETWEEN y0 AND y1 AND iz BETWEEN z0 - 2 AND z1 + 2 WHERE rise_velocity IS NOT NULL
),
around AS MATERIALIZED (
  SELECT step, bubble, region, count(*) AS voxels, avg(rise_velocity) AS mean_rise, CAST(count(*) FILTER (rise_velocity > 0) AS DOUBLE) / count(*) AS up_share, CAST(count(*) FILTER (rise_velocity < 0) AS DOUBLE) / count(*) AS down_share
  FROM near n WHERE region IS NOT NULL AND NOT EXISTS (SELECT 1 FROM bubbles o WHERE o.step = n.step AND o.voxel = n.voxel) GROUP BY step, bubble, region
)"""
TRUE_BUBBLES = reached("truth", "true_bubbles", t="_true")
DEGREES = "SELECT step + 1 AS step, 'merge' AS event FROM {0} GROUP BY step, dst HAVING count(*) > 1 UNION ALL SELECT step + 1, 'split' FROM {0} GROUP BY step, src HAVING count(*) > 1"
ACCURACY = f"""n AS (SELECT coalesce(f.step, t.step) AS step, count(*) FILTER (f.voxel IS NOT NULL AND t.voxel IS NOT NULL) AS hit, count(*) FILTER (f.voxel IS NULL) AS missed, count(*) FILTER (t.voxel IS NULL) AS extra FROM got f FULL JOIN truth t ON f.step = t.step AND f.voxel = t.voxel GROUP BY 1)
SELECT step, hit, missed, extra, round(CASE WHEN hit + extra > 0 THEN hit / CAST(hit + extra AS DOUBLE) END, 6) AS precision, round(CASE WHEN hit + missed > 0 THEN hit / CAST(hit + missed AS DOUBLE) END, 6) AS recall, round(hit / CAST(hit + missed + extra AS DOUBLE), 6) AS iou"""

SQL: dict[str, str] = {
    "particles_w1": f"WITH {PARTICLES} SELECT CAST(step AS INT) AS step, count(*) AS n, min(x) AS x_min, max(x) AS x_max, round(sum(y), 4) AS y_sum, round(sum(z), 4) AS z_sum, sum(vx) AS vx_sum FROM particles GROUP BY step",
    "particles_w2": f"WITH {BED} SELECT step, count(*) AS n, sum(vx) AS vx_sum FROM bed GROUP BY step",
    "planted_truth": f"WITH {LATTICE}, {truth('rise')}, {truth('shapes', 'other')} SELECT step, voxel, ix, iy, iz FROM truth UNION ALL SELECT step + 100, voxel, ix, iy, iz FROM other",
    "bounds": f"WITH {PARTICLES} SELECT {', '.join(f'min({a}) AS lo_{a}, max({a}) AS hi_{a}' for a in 'xyz')} FROM particles",
    "histogram": f"WITH {PARTICLES} SELECT CAST(step AS INT) AS step, ix, iy, iz, count(*) AS n, sum(vx) AS sum_vx, sum(vy) AS sum_vy FROM ({binned()}) GROUP BY ALL",
    "outside_bounds": "SELECT CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS step, count(*) FILTER (NOT (value BETWEEN 0 AND 200 AND user_id BETWEEN 0 AND 150)) AS outside FROM events GROUP BY 1",
    "density_dense": f"WITH {BED} SELECT step, voxel, density FROM field",
    "density_rebin": f"WITH {PARTICLES} SELECT CAST(step AS INT) AS step, ix, iy, iz, count(*) AS n, sum(vx) AS sum_vx FROM ({binned((12, 3, 12))}) GROUP BY ALL",
    "density_image_space": f"WITH {PARTICLES} SELECT CAST(step AS INT) AS step, ix, iy, iz, count(*) AS n, sum(vx) AS sum_vx FROM ({binned((24, 1, 24))}) GROUP BY ALL",
    "pvf": f"WITH {PARTICLES} SELECT CAST(step AS INT) AS step, {VOXEL} AS voxel, round(sum(vx) / count(*), 9) AS rise_velocity FROM ({binned()}) GROUP BY 1, 2",
    "pvf_dense": f"WITH {BED} SELECT step, voxel, round(rise_velocity, 9) AS rise_velocity, CASE WHEN rise_velocity IS NULL THEN 'empty' WHEN rise_velocity >= 2 THEN 'fast' WHEN rise_velocity > 0 THEN 'rising' WHEN rise_velocity < 0 THEN 'sinking' ELSE 'still' END AS motion FROM field",
    "smooth_density": f"WITH {BED}, k(o, w) AS (VALUES (-1, {d(1.0)}), (0, {d(2.0)}), (1, {d(1.0)})) SELECT f.step, f.voxel, round(sum(g.density * a.w * b.w * c.w) / sum(a.w * b.w * c.w), 9) AS estimate FROM field f, k a, k b, k c, field g WHERE g.step = f.step AND g.ix = f.ix + a.o AND g.iy = f.iy + b.o AND g.iz = f.iz + c.o GROUP BY ALL",
    "target_box": f"WITH {BED} SELECT step, voxel, density FROM field WHERE step = 0 AND ix BETWEEN 2 AND 4 AND iy BETWEEN 2 AND 3 AND iz BETWEEN 3 AND 4",
    "target_gaussian": f"WITH {BED}, {target(BOXES['rise'])} SELECT round(m0, 9) AS mu, round(s0, 9) AS sigma, n0 AS n FROM goal",
    "supervoxel_seeds": f"WITH {BED}, {seeds()} SELECT step, cluster, cx, cy, cz, cv FROM centres_0",
    "supervoxel_blocks": f"WITH {BED} SELECT step, voxel, {block()} AS cluster FROM field",
    "block_gaussians": f"{ON_BLOCKS} SELECT step, cluster, round(mu, 9) AS mu, round(sigma, 9) AS sigma, n FROM gauss",
    "supervoxel_iter1": f"WITH {BED}, {seeds()}, {iteration(1)} SELECT step, voxel, cluster FROM labels_1",
    "supervoxel_iter2": f"WITH {BED}, {seeds()}, {iteration(1)}, {iteration(2)} SELECT step, voxel, cluster FROM labels_2",
    "bhattacharyya_std": f"{ON_BLOCKS}, {distance('std', 6)} SELECT step, cluster, distance FROM dist",
    "bhattacharyya_var": f"{ON_BLOCKS}, {distance('var', 6)} SELECT step, cluster, distance FROM dist",
    "bsf_max": f"{BLOCK_BSF} SELECT step, voxel, round(similarity, 6) AS similarity FROM bsf",
    "bsf_minmax": f"{ON_BLOCKS}, {distance()}, {bsf('minmax')} SELECT step, voxel, round(similarity, 6) AS similarity FROM bsf",
    "bsf_coefficient": f"{ON_BLOCKS}, {distance()}, {bsf('coefficient')} SELECT step, voxel, round(similarity, 6) AS similarity FROM bsf",
    "bsf_run_scope": f"{ON_BLOCKS}, {distance()}, {bsf('max', 'run')} SELECT step, voxel, round(similarity, 6) AS similarity FROM bsf",
    "segmented": f"{RUN} SELECT step, voxel FROM bsf WHERE similarity >= {d(0.92)}",
    "segment_sweep": f"{RUN}, t(threshold) AS (VALUES {', '.join(f'({d(v)})' for v in (0.88, 0.9, 0.92, 0.94, 0.96))}) SELECT threshold, step, count(*) AS voxels FROM bsf JOIN t ON similarity >= threshold GROUP BY ALL",
    "segment_levels": f"{RUN} SELECT step, voxel, CASE WHEN similarity >= {d(0.92)} THEN {d(0.92)} WHEN similarity >= {d(0.8)} THEN {d(0.8)} ELSE {d(0.5)} END AS level FROM bsf WHERE similarity >= {d(0.5)}",
    "threshold_profile": f"{RUN} SELECT step, bin, voxels, CAST(sum(voxels) OVER (PARTITION BY step ORDER BY bin DESC) AS BIGINT) AS above FROM (SELECT step, CAST(least(floor(similarity * 20), 19) AS INT) AS bin, count(*) AS voxels FROM bsf GROUP BY ALL)",
    "components_6": f"{LABELS} SELECT step, voxel, bubble FROM found",
    "components_18": f"WITH RECURSIVE {run()}, {segments()}, {reached('seg', 'found', 18)} SELECT step, voxel, bubble FROM found",
    "components_26": f"WITH RECURSIVE {run()}, {segments()}, {reached('seg', 'found', 26)} SELECT step, voxel, bubble FROM found",
    "components_tiled": f"{LABELS} SELECT step, voxel, bubble FROM found",
    "bubble_traits": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels, {', '.join(f'round({c}, 6) AS {c}' for c in ('volume', 'xc', 'yc', 'zc', 'aspect'))}, ix_min, ix_max, iz_min, iz_max, is_freeboard FROM described",
    "trait_moments": f"{LABELS}, {TRAITS} SELECT step, bubble, round(CAST(greatest(iy_max - iy_min, iz_max - iz_min) + 1 AS DOUBLE) / (ix_max - ix_min + 1), 6) AS aspect, round(sqrt(vz + {d(1 / 12)}) / sqrt(vx + {d(1 / 12)}), 6) AS aspect_moments FROM described",
    "overlap_edges": f"{EDGES} SELECT step, src, dst, inter, size_a, size_b FROM edges",
    "overlap_edges_window": f"{EDGES} SELECT step, src, dst, inter, size_a, size_b FROM edges",
    "dice_edges": f"{EDGES} SELECT step, src, dst, round(dice, 9) AS dice FROM edges",
    "jaccard_edges": f"{EDGES} SELECT step, src, dst, round(jaccard, 9) AS jaccard FROM edges",
    "overlap_coefficient_edges": f"{EDGES} SELECT step, src, dst, round(overlap, 9) AS overlap FROM edges",
    "box_edges": f"{LABELS}, {TRAITS} SELECT a.step, a.bubble AS src, b.bubble AS dst FROM traits a JOIN traits b ON b.step = a.step + 1 AND {' AND '.join(f'a.i{x}_min <= b.i{x}_max AND b.i{x}_min <= a.i{x}_max' for x in 'xyz')}",
    "links_without_confidence": f"{EDGES} SELECT step, src, arg_min(dst, row(-inter, dst)) AS dst, max(inter) AS inter FROM edges GROUP BY step, src",
    "best_forward": f"{EDGES}, {BEST} SELECT step, src, dst, inter, round(dice, 9) AS dice FROM ahead_best",
    "best_backward": f"{EDGES}, {BEST} SELECT step, src, dst, inter, round(dice, 9) AS dice FROM back_best",
    "track_single": f"{SINGLE} SELECT track, step, bubble, round(dice, 9) AS dice FROM tracks",
    "track_single_recursive": f"{SINGLE} SELECT track, step, bubble, round(dice, 9) AS dice FROM tracks",
    "track_collective": f"{TRACED} SELECT track, step, bubble, round(dice, 9) AS dice FROM tracks",
    "track_all": f"{EDGES}, {BEST}, {mutual_chains()} SELECT track, step, bubble, round(dice, 9) AS dice FROM chain",
    "rise_velocity": f"{MOVING} SELECT track, step, bubble, round(rise_velocity, 4) AS rise_velocity FROM moved",
    "low_dice_flag": f"""{FOLLOWED} SELECT track, step, coalesce(dice < {d(0.3)} OR (count(dice) OVER w >= 2 AND dice < round(avg(dice) OVER w - {d(2.0)} * stddev_pop(dice) OVER w, 12) - {d(1e-9)}), false) AS low_confidence
FROM followed WINDOW w AS (PARTITION BY track ORDER BY step ROWS BETWEEN 5 PRECEDING AND 1 PRECEDING)""",
    "volume_events": f"{MOVING} SELECT track, step, round(change, 6) AS change, CASE WHEN change >= {d(0.5)} THEN 'merge' WHEN change <= {d(-0.33)} THEN 'split' END AS event FROM moved",
    "graph_events": f"{EDGES} SELECT CAST(step + 1 AS INT) AS step, dst AS bubble, 'merge' AS event, count(*) AS degree FROM edges GROUP BY step, dst HAVING count(*) > 1 UNION ALL SELECT CAST(step + 1 AS INT), src, 'split', count(*) FROM edges GROUP BY step, src HAVING count(*) > 1",
    "births_deaths": f"""{SHAPES}, {TRAITS}, {edges()} SELECT step, bubble, 'birth' AS event FROM traits t WHERE step > (SELECT min(step) FROM traits) AND NOT EXISTS (SELECT 1 FROM edges e WHERE e.step + 1 = t.step AND e.dst = t.bubble)
UNION ALL SELECT step, bubble, CASE WHEN ix_max >= 18 THEN 'burst' ELSE 'dissipation' END FROM traits t WHERE step < (SELECT max(step) FROM traits) AND NOT EXISTS (SELECT 1 FROM edges e WHERE e.step = t.step AND e.src = t.bubble)""",
    "event_counts": f"{EDGES} SELECT event, count(*) AS n FROM (SELECT 'merge' AS event FROM edges GROUP BY step, dst HAVING count(*) > 1 UNION ALL SELECT 'split' FROM edges GROUP BY step, src HAVING count(*) > 1) GROUP BY event",
    "track_summary": f"""{FOLLOWED} SELECT track, min(step) AS first_step, max(step) AS last_step, max(step) - min(step) + 1 AS lifetime, round(coalesce(sum(way), 0), 4) AS path_length, round(max(volume), 4) AS max_volume, arg_max(step, row(volume, -step)) AS max_volume_step
FROM (SELECT *, abs(xc - lag(xc) OVER (PARTITION BY track ORDER BY step)) AS way FROM followed) GROUP BY track""",
    "query_panel": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels, round(aspect, 6) AS aspect FROM described WHERE aspect BETWEEN {d(0.6)} AND {d(1.4)} AND voxels BETWEEN 25 AND 45",
    "query_centred": f"{LABELS}, {TRAITS} SELECT step, bubble FROM described WHERE aspect BETWEEN {d(1.0 - 0.3)} AND {d(1.0 + 0.3)}",
    "spherical": f"{LABELS}, {TRAITS} SELECT step, bubble FROM described WHERE abs(aspect - 1) <= {d(0.2)}",
    "largest_brush": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels FROM described WHERE voxels >= (SELECT quantile_cont(voxels, 0.75) FROM described)",
    "parallel_axes": f"""{LABELS}, {TRAITS}, ends AS (SELECT min(voxels) AS v0, max(voxels) AS v1, min(aspect) AS a0, max(aspect) AS a1, min(xc) AS x0, max(xc) AS x1 FROM described)
SELECT step, bubble, CAST(0 AS INT) AS place, 'voxels' AS axis, CAST(voxels AS DOUBLE) AS value, round(CAST(voxels - v0 AS DOUBLE) / (v1 - v0), 6) AS scaled FROM described, ends
UNION ALL SELECT step, bubble, 1, 'aspect', round(aspect, 4), round((aspect - a0) / (a1 - a0), 6) FROM described, ends UNION ALL SELECT step, bubble, 2, 'xc', round(xc, 4), round((xc - x0) / (x1 - x0), 6) FROM described, ends""",
    "scatter_bins": f"""{LABELS}, {TRAITS}, ends AS (SELECT min(step) AS a0, max(step) AS a1, min(voxels) AS b0, max(voxels) AS b1 FROM described)
SELECT CAST(least(floor(CAST(step - a0 AS DOUBLE) / (a1 - a0) * 5), 4) AS INT) AS ia, CAST(least(floor(CAST(voxels - b0 AS DOUBLE) / (b1 - b0) * 5), 4) AS INT) AS ib, count(*) AS n FROM described, ends GROUP BY 1, 2""",
    "splom": f"""{FOLLOWED} SELECT track, step, 'voxels' AS row_trait, 'step' AS col_trait, CAST(voxels AS DOUBLE) AS y, CAST(step AS DOUBLE) AS x, round(dice, 9) AS color FROM followed
UNION ALL SELECT track, step, 'xc', 'step', round(xc, 4), step, round(dice, 9) FROM followed UNION ALL SELECT track, step, 'xc', 'voxels', round(xc, 4), voxels, round(dice, 9) FROM followed""",
    "correlations": f"""{FOLLOWED} SELECT 'voxels' AS row_trait, 'step' AS col_trait, round(corr(voxels, step), 6) AS r FROM followed WHERE track = {LARGEST}
UNION ALL SELECT 'xc', 'step', round(corr(xc, step), 6) FROM followed WHERE track = {LARGEST} UNION ALL SELECT 'xc', 'voxels', round(corr(xc, voxels), 6) FROM followed WHERE track = {LARGEST}""",
    "trends": f"{MOVING} SELECT track, round(corr(volume, rise_velocity), 6) AS volume_velocity_r, round(regr_slope(volume, step), 3) AS volume_per_step, round(regr_r2(volume, step), 6) AS volume_fit, count(*) AS n FROM moved GROUP BY track",
    "growth_share": f"{FOLLOWED} SELECT count(*) FILTER (b > a) AS grown, count(*) AS tracks, avg(CASE WHEN b > a THEN 1.0 ELSE 0.0 END) AS share FROM (SELECT track, arg_min(volume, step) AS a, arg_max(volume, step) AS b FROM followed GROUP BY track HAVING count(*) >= 2)",
    "velocity_by_volume": f"""{MOVING} SELECT CASE WHEN change > {d(0.05)} THEN 'grows' WHEN change < {d(-0.05)} THEN 'falls' ELSE 'stays' END AS direction, count(*) AS n, round(avg(rise_velocity), 3) AS mean_velocity, round(avg(dv), 3) AS mean_change
FROM (SELECT *, rise_velocity - lag(rise_velocity) OVER (PARTITION BY track ORDER BY step) AS dv FROM moved) WHERE change IS NOT NULL GROUP BY 1""",
    "compare_tracks": f"{FOLLOWED} SELECT CAST(t AS INT) AS step, k.track, round(v, 4) AS volume FROM range(12) r(t) CROSS JOIN (SELECT DISTINCT track FROM followed) k LEFT JOIN (SELECT track, step, max(volume) AS v FROM followed GROUP BY ALL) f ON f.track = k.track AND f.step = t",
    "event_window": f"{MOVING} SELECT track, step, CASE WHEN change >= {d(0.5)} THEN 'merge' WHEN change <= {d(-0.33)} THEN 'split' END AS event FROM moved WHERE step BETWEEN 4 AND 8",
    "projection_xz": f"{LABELS} SELECT step, bubble, ix, iz, CAST(count(*) AS DOUBLE) AS value FROM bubbles GROUP BY ALL",
    "images": f"{LABELS} SELECT step, bubble, {NZ} AS width, {NX} AS height, {NX * NZ} AS pixels, CAST(count(*) AS DOUBLE) AS total FROM bubbles GROUP BY step, bubble",
    "density_threshold_baseline": f"WITH {BED} SELECT step, voxel FROM field WHERE density <= 5",
    "void_fraction_baseline": f"WITH {BED} SELECT step, voxel FROM field WHERE greatest({d(1.0)} - density / {d(30.0)}, 0) >= {d(0.75)}",
    "accuracy_voxels": f"""{RUN}, got AS (SELECT step, voxel FROM bsf WHERE similarity >= {d(0.92)} AND voxel < {20 * NY * NZ}), {ACCURACY} FROM n""",
    "compactness": f"{ON_BLOCKS} SELECT step, count(*) AS raw_values, count(DISTINCT cluster) * 2 AS distribution_values, CAST(count(DISTINCT cluster) * 2 AS DOUBLE) / count(*) AS ratio FROM labels GROUP BY step",
    "dice_profile": f"{EDGES} SELECT count(*) AS links, round(min(dice), 9) AS lowest, round(avg(dice), 9) AS mean, round(quantile_cont(dice, 0.5), 9) AS median, round(max(dice), 9) AS highest FROM edges",
    "sensitivity_cube": f"""{RUN}, t(threshold) AS (VALUES {', '.join(f'({d(v)})' for v in (0.88, 0.92, 0.96))}), per AS (SELECT threshold, step, count(*) AS voxels FROM bsf JOIN t ON similarity >= threshold GROUP BY ALL)
SELECT threshold, step, count(*) AS bubbles, CAST(sum(voxels) AS BIGINT) AS voxels FROM per GROUP BY CUBE (threshold, step)""",
    "strided_dice": f"{LABELS}, {', '.join(edges(g, f'e{g}') for g in (1, 2, 4, 8))} {' UNION ALL '.join(f'SELECT {g} AS gap, count(*) AS links, round(avg(dice), 9) AS mean FROM e{g}' for g in (1, 2, 4, 8))}",
    "ensemble_rollup": f"""WITH {PARTICLES.replace("SELECT year", "SELECT l_orderkey, year")}, h AS (SELECT r_name AS member, CAST(step AS INT) AS step FROM ({binned()}) b JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)
SELECT member, step, count(*) AS n FROM h GROUP BY ROLLUP (member, step)""",
    "material_density": f"""WITH {PARTICLES.replace("SELECT year", "SELECT l_partkey, year")}, h AS (SELECT p_size AS diameter, step, ix, iy, iz, count(*) AS n, sum(vx) AS s FROM ({binned((6, 2, 6))}) b JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL)
SELECT diameter, CAST(sum(n) AS BIGINT) AS particles, count(*) AS bins, sum(s) AS momentum FROM h GROUP BY diameter""",
    "order_bed_histogram": f"""WITH o AS (SELECT CAST(year(o_orderdate) - 1995 AS INT) AS step, o_totalprice AS x, CAST(substr(o_orderpriority, 1, 1) AS DOUBLE) - 1 + (o_orderkey % 64) / {d(64.0)} AS y, o_custkey % 50 + (o_orderkey % 64) / {d(64.0)} AS z, CASE o_orderstatus WHEN 'F' THEN {d(1.0)} WHEN 'P' THEN {d(-1.0)} ELSE {d(0.0)} END AS vx FROM orders)
SELECT step, ix, iy, iz, count(*) AS n, sum(vx) AS sum_vx FROM ({binned((12, 3, 12), "o", {"x": (900.0, 450000.0), "y": (0.0, 5.0), "z": (0.0, 51.0)})}) GROUP BY ALL""",
    "event_hist_daily": f"""WITH e AS (SELECT CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS step, least(value, {d(200.0)}) AS x, CAST(hour(ts) AS DOUBLE) AS y, CAST(user_id AS DOUBLE) AS z, CASE event_type WHEN 'click' THEN {d(2.0)} WHEN 'view' THEN {d(1.0)} WHEN 'signup' THEN {d(0.0)} WHEN 'purchase' THEN {d(-1.0)} ELSE {d(-2.0)} END AS vx FROM events)
SELECT step, count(*) AS n, sum(vx) AS momentum, count(DISTINCT row(ix, iy, iz)) AS bins FROM ({binned((20, 6, 15), "e", {"x": (0.0, 200.0), "y": (0.0, 24.0), "z": (0.0, 150.0)})}) GROUP BY step""",
    "event_sliding": "SELECT strftime(b - k * INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS b FROM events), range(4) r(k) GROUP BY 1",
    "asof_step": f"{LABELS}, per AS (SELECT step, count(DISTINCT bubble) AS bubbles FROM bubbles GROUP BY step) SELECT p.step, p.bubbles, q.step AS stored_step, q.bubbles AS stored FROM per p LEFT JOIN per q ON q.step % 4 = 0 AND q.step = (SELECT max(step) FROM per r WHERE r.step % 4 = 0 AND r.step <= p.step)",
    "interval_join": f"{EDGES}, {BEST}, {mutual_chains()}, lives AS (SELECT track, min(step) AS a, max(step) AS b FROM chain GROUP BY track) SELECT s.step, track FROM (SELECT DISTINCT step FROM bubbles) s JOIN lives ON s.step BETWEEN a AND b",
    "morton_order": f"{LABELS} SELECT step, voxel, CAST({' + '.join(f'(((CAST({i} AS BIGINT) >> {k}) & 1) << {3 * k + p})' for k in range(5) for p, i in enumerate(('ix', 'iy', 'iz')))} AS BIGINT) AS morton FROM bubbles",
    "bins_by_bucket": f"WITH {PARTICLES} SELECT {', '.join(f'CAST(least(floor({d(float(n))} * ({a} - {d(SPANS[a][0])}) / ({d(SPANS[a][1])} - {d(SPANS[a][0])})), {n - 1}) AS INT) AS i{a}' for a, n in zip('xyz', (NX, NY, NZ), strict=True))}, count(*) AS n FROM ({binned()}) GROUP BY 1, 2, 3",
    "void_voxels": f"WITH {BED} SELECT step, voxel, density FROM truth JOIN field USING (step, voxel)",
    "range_join": f"{LABELS}, {TRAITS} SELECT a.step, a.bubble AS a, b.bubble AS b FROM described a JOIN described b ON b.step = a.step + 1 AND abs(a.xc - b.xc) <= 6000 AND abs(a.zc - b.zc) <= 4",
    "top_bubbles": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels FROM (SELECT *, row_number() OVER (PARTITION BY step ORDER BY voxels DESC, bubble) AS r FROM described) WHERE r <= 2",
    "unpivoted": f"{LABELS}, {TRAITS} SELECT step, bubble, 'voxels' AS name, CAST(voxels AS DOUBLE) AS value FROM traits UNION ALL SELECT step, bubble, 'ix_min', ix_min FROM traits UNION ALL SELECT step, bubble, 'ix_max', ix_max FROM traits",
    "moving_volume": f"{FOLLOWED} SELECT track, step, round(avg(voxels) OVER (PARTITION BY track ORDER BY step RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING), 9) AS moving_mean FROM followed",
    "set_operations": f"""{LABELS}, a AS (SELECT voxel FROM bubbles WHERE step = 3), b AS (SELECT voxel FROM bubbles WHERE step = 4)
SELECT 'intersect' AS kind, count(*) AS n, CAST(sum(voxel) AS BIGINT) AS total FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'union', count(*), CAST(sum(voxel) AS BIGINT) FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'except', count(*), CAST(sum(voxel) AS BIGINT) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)""",
    "dice_array_sets": f"{LABELS}, a AS (SELECT voxel FROM bubbles WHERE step = 3), b AS (SELECT voxel FROM bubbles WHERE step = 4) SELECT round({d(2.0)} * (SELECT count(*) FROM a JOIN b USING (voxel)) / ((SELECT count(*) FROM a) + (SELECT count(*) FROM b)), 9) AS dice",
    "event_json": "SELECT event_type, count(k) AS n, CAST(sum(k) AS BIGINT) AS total FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events) GROUP BY event_type",
    "quality_points": "SELECT lang, quality, count(*) AS n, min(n_chars) AS shortest, max(n_chars) AS longest FROM documents JOIN labels USING (doc_id) GROUP BY lang, quality",
    "supervoxel_array": f"{RUN} SELECT step, voxel, cluster FROM labels",
    "supervoxel_report": f"WITH {BED}, {clustered()}, rounds AS ({' UNION ALL '.join(f'SELECT step, {k} AS iteration, count(*) FILTER (moved) AS changed, sum(tested) AS distances FROM labels_{k} GROUP BY step' for k in range(1, 21))}) SELECT step, CAST(iteration AS INT) AS iteration, changed, CAST(distances AS BIGINT) AS distances, changed = 0 AS converged FROM rounds r WHERE NOT EXISTS (SELECT 1 FROM rounds b WHERE b.step = r.step AND b.iteration < r.iteration AND b.changed = 0)",
    "supervoxel_gaussians": f"{RUN} SELECT step, cluster, round(mu, 9) AS mu, round(sigma, 9) AS sigma, n FROM gauss",
    "supervoxel_value_only": f"WITH {BED}, {clustered(gamma=0.0, rounds=4)} SELECT step, voxel, cluster FROM labels",
    "supervoxel_place_only": f"WITH {BED}, {clustered(gamma=1.0, rounds=4)} SELECT step, voxel, cluster FROM labels",
    "bsf_supervoxels": f"{RUN} SELECT step, voxel, round(similarity, 6) AS similarity FROM bsf",
    "freeboard": f"{LABELS} SELECT step, bubble, max(ix) = {NX - 1} AS is_freeboard FROM found GROUP BY step, bubble",
    "traits_weighted": f"{LABELS} SELECT step, bubble, {', '.join(f'round(sum(similarity * ({d(SPANS[a][0])} + (i{a} + {d(0.5)}) * {d(W[i])})) / sum(similarity), 4) AS {a}c' for i, a in enumerate('xyz'))} FROM bubbles JOIN bsf USING (step, voxel) GROUP BY step, bubble",
    "lookup": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels FROM described WHERE (step, bubble) IN ({SEED})",
    "scene_layers": f"""{SINGLE}, own AS (SELECT DISTINCT step, bubble FROM tracks)
SELECT 'tracked' AS layer, b.step, voxel, CAST(b.bubble AS DOUBLE) AS value FROM bubbles b JOIN own USING (step, bubble)
UNION ALL SELECT 'others', b.step, voxel, b.bubble FROM bubbles b WHERE NOT EXISTS (SELECT 1 FROM own o WHERE o.step = b.step AND o.bubble = b.bubble)
UNION ALL SELECT 'fast', step, voxel, round(rise_velocity, 9) FROM field WHERE rise_velocity >= 2""",
    "flow_around": f"{LABELS}, {AROUND} SELECT step, bubble, region, voxels, round(mean_rise, 6) AS mean_rise, round(up_share, 6) AS up_share, round(down_share, 6) AS down_share FROM around",
    "wake_contrast": f"{LABELS}, {AROUND} SELECT step, bubble, round(below, 6) AS below, round(above, 6) AS above, round(side, 6) AS side, round(below - above, 6) AS contrast FROM (SELECT step, bubble, max(mean_rise) FILTER (region = 'below') AS below, max(mean_rise) FILTER (region = 'above') AS above, max(mean_rise) FILTER (region = 'side') AS side FROM around GROUP BY ALL)",
    "accuracy_bubbles": f"{LABELS}, {TRUE_BUBBLES} SELECT t.step, t.bubble, count(*) AS voxels, count(b.voxel) AS covered, count(b.voxel) >= count(*) * {d(0.5)} AS recalled FROM true_bubbles t LEFT JOIN bubbles b USING (step, voxel) GROUP BY t.step, t.bubble",
    "tracking_accuracy": f"""{LABELS}, {edges()}, {best()}, {mutual_chains()}, {TRUE_BUBBLES}, {edges(name='true_edges', bubbles='true_bubbles')}, {best('true_edges', '_t')}, {mutual_chains('_t', 'true_bubbles', 'true_chain')},
a AS (SELECT c.track AS true_track, c.step, b.voxel FROM true_chain c JOIN true_bubbles b USING (step, bubble)),
g AS (SELECT c.track, c.step, b.voxel FROM chain c JOIN bubbles b USING (step, bubble)),
most AS (SELECT true_track, step, arg_max(track, row(n, -track)) AS track FROM (SELECT true_track, a.step, track, count(*) AS n FROM a JOIN g ON a.step = g.step AND a.voxel = g.voxel GROUP BY ALL) GROUP BY ALL),
moved AS (SELECT true_track, coalesce(lag(track) OVER (PARTITION BY true_track ORDER BY step) <> track, false) AS switch FROM most)
SELECT true_track, steps, coalesce(covered, 0) AS covered, coalesce(switches, 0) AS switches FROM (SELECT track AS true_track, count(DISTINCT step) AS steps FROM true_chain GROUP BY track) LEFT JOIN (SELECT true_track, count(*) AS covered, count(*) FILTER (switch) AS switches FROM moved GROUP BY true_track) USING (true_track)""",
    "event_accuracy": f"""{EDGES}, {TRUE_BUBBLES}, {edges(name='true_edges', bubbles='true_bubbles')},
f AS (SELECT step, event, count(*) AS f FROM ({DEGREES.format('edges')}) GROUP BY ALL), t AS (SELECT step, event, count(*) AS t FROM ({DEGREES.format('true_edges')}) GROUP BY ALL)
SELECT event, CAST(sum(least(f, t)) AS BIGINT) AS hit, CAST(sum(greatest(t - f, 0)) AS BIGINT) AS missed, CAST(sum(greatest(f - t, 0)) AS BIGINT) AS extra FROM (SELECT coalesce(f.event, t.event) AS event, coalesce(f, 0) AS f, coalesce(t, 0) AS t FROM f FULL JOIN t ON f.step = t.step AND f.event = t.event) GROUP BY event""",
    "merged_moments": f"WITH {BED}, {partition()}, {gaussians()} SELECT step, cluster, round(mu, 9) AS mu, round(sigma, 9) AS sigma, n FROM gauss",
    "density_threshold_12": f"WITH {BED} SELECT step, voxel FROM field WHERE density <= 12",
    "pixels": f"{LABELS} SELECT step, bubble, ({NX - 1} - ix) * {NZ} + iz AS pixel, round(max(similarity), 4) AS value FROM bubbles JOIN bsf USING (step, voxel) GROUP BY step, bubble, ix, iz",
}

PER_CLUSTER = "per AS (SELECT step, cluster, count(*) AS n, sum(density) AS s1, sum(density * density) AS s2 FROM labels GROUP BY ALL), v AS (SELECT step, round(CAST(sum(s2 - CAST(s1 AS DOUBLE) * s1 / n) AS DOUBLE) / sum(n), 6) AS within, round(CAST(sum(s2) AS DOUBLE) / sum(n) - (CAST(sum(s1) AS DOUBLE) / sum(n)) * (CAST(sum(s1) AS DOUBLE) / sum(n)), 6) AS total FROM per GROUP BY step)"
SQL |= {
    "homogeneity": f"{ON_BLOCKS}, {PER_CLUSTER} SELECT step, within, total, round(within / total, 5) AS ratio FROM v",
    "reconstruction_rmse": f"{ON_BLOCKS}, {PER_CLUSTER} SELECT step, round(sqrt(within), 5) AS rmse FROM v",
    "trait_fields": f"{LABELS} SELECT b.step, b.bubble, round(avg(similarity), 6) AS mean_similarity, round(avg(rise_velocity), 6) AS mean_rise FROM bubbles b JOIN bsf USING (step, voxel) JOIN field f USING (step, voxel) GROUP BY b.step, b.bubble",
}


def recalled(t: str, size: int, how: str) -> str:
    return f"SELECT {size} AS size, '{how}' AS partition, voxels <= 14 AS small, covered >= voxels * {d(0.5)} AS recalled FROM (SELECT t.step, t.bubble, count(*) AS voxels, count(b.voxel) AS covered FROM true_bubbles t LEFT JOIN bsf{t} b ON b.step = t.step AND b.voxel = t.voxel AND b.similarity >= {d(0.92)} GROUP BY ALL)"


def parts_of(size: int) -> str:
    out = []
    for t, made in ((f"_s{size}", clustered(f"_s{size}", size=size)), (f"_b{size}", partition(f"_b{size}", size=size))):
        out += [made, gaussians(t), distance(t=t), bsf(t=t)]
    return ", ".join(out)


OVERALL = f"""SELECT hit, missed, extra, round(CASE WHEN hit + extra > 0 THEN hit / CAST(hit + extra AS DOUBLE) END, 6) AS precision, round(CASE WHEN hit + missed > 0 THEN hit / CAST(hit + missed AS DOUBLE) END, 6) AS recall, round(CASE WHEN hit + missed + extra > 0 THEN hit / CAST(hit + missed + extra AS DOUBLE) END, 6) AS iou FROM (
  SELECT count(*) FILTER (f.voxel IS NOT NULL AND t.voxel IS NOT NULL) AS hit, count(*) FILTER (f.voxel IS NULL) AS missed, count(*) FILTER (t.voxel IS NULL) AS extra FROM {{}} f FULL JOIN truth t ON f.step = t.step AND f.voxel = t.voxel)"""


def with_bins(n: tuple[int, int, int]) -> str:
    """Bubbles found with other numbers of bins, as a query of its own."""
    w = [(hi - lo) / k for (lo, hi), k in zip((SPANS[a] for a in "xyz"), n, strict=True)]
    return f"""SELECT '{"x".join(map(str, n))}' AS bins, * FROM (WITH RECURSIVE {run(n=n, box=void_box(bed_grid(n)), cells=True)}, {segments()}, {reached('seg', 'found')}, {kept(n=n)},
count_ AS (SELECT count(*) AS bubbles, round(sum(v), 3) AS volume FROM (SELECT count(*) * {d(w[0] * w[1] * w[2])} AS v FROM bubbles GROUP BY step, bubble)), overall AS ({OVERALL.format("bubbles")}) SELECT * FROM count_ CROSS JOIN overall)"""


def compared(case: str, n: tuple[int, int, int], source: str = PARTICLES, spans: dict | None = None) -> str:
    """Similarity and density thresholds on one bed, as a query of its own; the tuned threshold comes from `tuned`."""
    grid = order_grid(n) if spans else bed_grid(n)
    name = "x".join(map(str, n))
    top = f"(ix + {d(0.5)}) / {d(float(n[0]))} < {d(0.85)}"
    found = {
        "similarity": f"SELECT b.step, b.voxel FROM bsf b JOIN lattice USING (voxel) WHERE similarity >= {d(0.92)} AND {top}",
        "density tuned on lines": f"SELECT step, voxel FROM field WHERE density <= (SELECT fixed FROM tuned) AND {top}",
        "density 12": f"SELECT step, voxel FROM field WHERE density <= 12 AND {top}",
    }
    each = " UNION ALL ".join(f"SELECT '{case}' AS \"case\", '{name}' AS bins, '{k}' AS method, * FROM ({OVERALL.format(f'({q})')})" for k, q in found.items())
    return f"SELECT * FROM (WITH {bed('rise', None, n, source, spans)}, {target(void_box(grid))}, {clustered(n=n)}, {gaussians()}, {distance()}, {bsf()} {each})"


def global_rounds(k: int, rounds: int) -> str:
    """K-means of all voxels with all centres, round by round; centres are picked along the voxels' numbers."""
    out = [f"""kc_0 AS MATERIALIZED (SELECT step, c AS cluster, CAST(ix AS DOUBLE) AS cx, CAST(iy AS DOUBLE) AS cy, CAST(iz AS DOUBLE) AS cz, CAST(density AS DOUBLE) AS cv FROM range({k}) r(c) JOIN field ON voxel = CAST(round_even(c * ({d((G - 1) / (k - 1))}), 0) AS BIGINT)),
kl_0 AS MATERIALIZED (SELECT step, voxel, CAST(-1 AS BIGINT) AS cluster FROM field)"""]
    px = " + ".join(f"(i{a} - c{a}) * (i{a} - c{a})" for a in "xyz")
    for i in range(1, rounds + 1):
        out.append(f"""kl_{i} AS MATERIALIZED (SELECT f.step, f.voxel, arg_min(c.cluster, row({d(0.3)} * sqrt({px}) + {d(0.7)} * abs(density - cv), c.cluster)) AS cluster FROM field f JOIN kc_{i - 1} c ON f.step = c.step GROUP BY ALL),
kc_{i} AS MATERIALIZED (SELECT c.step, c.cluster, {", ".join(f"coalesce(m.m{a}, c.c{a}) AS c{a}" for a in "xyz")}, coalesce(m.mv, c.cv) AS cv FROM kc_{i - 1} c LEFT JOIN (SELECT step, cluster, {", ".join(f"CAST(sum(i{a}) AS DOUBLE) / count(*) AS m{a}" for a in "xyz")}, CAST(sum(density) AS DOUBLE) / count(*) AS mv FROM kl_{i} JOIN field USING (step, voxel) GROUP BY ALL) m USING (step, cluster))""")
    each = " UNION ALL ".join(f"SELECT a.step, CAST({i} AS INT) AS iteration, count(*) FILTER (a.cluster <> b.cluster) AS changed, count(*) * {k} AS distances FROM kl_{i} a JOIN kl_{i - 1} b USING (step, voxel) GROUP BY a.step" for i in range(1, rounds + 1))
    return ", ".join(out) + f", all_rounds AS MATERIALIZED ({each}), global_rounds AS MATERIALIZED (SELECT * FROM all_rounds r WHERE NOT EXISTS (SELECT 1 FROM all_rounds b WHERE b.step = r.step AND b.iteration < r.iteration AND b.changed = 0))"


THRESHOLDS = (0.88, 0.9, 0.92, 0.94, 0.96)
STEPPED = "(xc - lag(xc) OVER w) / (step - lag(step) OVER w)"
FIRST = SEED.replace("step = 5", "step = 0")
LAYERS = """own AS (SELECT DISTINCT step, bubble FROM tracks)
SELECT layer, step, count(*) AS voxels FROM (
  SELECT 'tracked' AS layer, b.step FROM bubbles b JOIN own USING (step, bubble)
  UNION ALL SELECT 'others', b.step FROM bubbles b WHERE NOT EXISTS (SELECT 1 FROM own o WHERE o.step = b.step AND o.bubble = b.bubble)
  UNION ALL SELECT 'fast', step FROM field WHERE rise_velocity >= 2) GROUP BY layer, step"""
BOX_LINKS = "SELECT DISTINCT a.step, a.bubble AS src, b.bubble AS dst FROM {0} a JOIN {0} b ON b.step = a.step + 1 AND " + " AND ".join(f"a.i{x}_min <= b.i{x}_max AND b.i{x}_min <= a.i{x}_max" for x in "xyz")
ENDS = "SELECT step, bubble, " + ", ".join(f"min(i{a}) AS i{a}_min, max(i{a}) AS i{a}_max" for a in "xyz") + " FROM {} GROUP BY step, bubble"
H = {(i, j): f"(({'p.c' + str(min(i, j)) + str(max(i, j))} + q.c{min(i, j)}{max(i, j)}) / {d(2.0)})" for i in range(3) for j in range(3)}


def det(m: dict) -> str:
    return " + ".join(f"{m[0, i]} * ({m[1, (i + 1) % 3]} * {m[2, (i + 2) % 3]} - {m[1, (i + 2) % 3]} * {m[2, (i + 1) % 3]})" for i in range(3))


def own(t: str) -> dict:
    return {(i, j): f"{t}.c{min(i, j)}{max(i, j)}" for i in range(3) for j in range(3)}


#: Entries of the adjugate of the mean covariance.
ADJ = {(i, j): f"({H[(j + 1) % 3, (i + 1) % 3]} * {H[(j + 2) % 3, (i + 2) % 3]} - {H[(j + 1) % 3, (i + 2) % 3]} * {H[(j + 2) % 3, (i + 1) % 3]})" for i in range(3) for j in range(3)}
SQL |= {
    "mv_bhattacharyya": f"""WITH v AS (SELECT label, CAST(embedding[1] AS DOUBLE) AS x0, CAST(embedding[2] AS DOUBLE) AS x1, CAST(embedding[3] AS DOUBLE) AS x2 FROM embeddings),
g AS (SELECT label, {", ".join(f"avg(x{i}) AS m{i}" for i in range(3))}, {", ".join(f"covar_pop(x{i}, x{j}) + {d(1e-9 if i == j else 0.0)} AS c{i}{j}" for i in range(3) for j in range(i, 3))} FROM v GROUP BY label)
SELECT p.label AS label_a, q.label AS label_b, round(({" + ".join(f"(p.m{i} - q.m{i}) * {ADJ[i, j]} * (p.m{j} - q.m{j})" for i in range(3) for j in range(3))}) / ({det(H)}) / 8 + {d(0.5)} * (ln({det(H)}) - {d(0.5)} * (ln({det(own("p"))}) + ln({det(own("q"))}))), 8) AS distance FROM g p JOIN g q ON p.label < q.label""",
    "kmeans_global": f"WITH {BED}, {global_rounds(64, 5)} SELECT step, iteration, changed, distances FROM global_rounds",
    "workload_e1": f"WITH {BED}, {target(BOXES['rise'])}, whole AS ({target(Box((0, 19), (0, NY - 1), (0, NZ - 1))).partition('(')[2][:-1]}) SELECT 'target' AS region, round(m0, 9) AS mu, round(s0, 9) AS sigma, n0 AS n FROM goal UNION ALL SELECT 'bed', round(m0, 9), round(s0, 9), n0 FROM whole",
    "workload_e2": f"{RUN} SELECT step, voxel, round(similarity, 6) AS similarity, round(rise_velocity, 9) AS rise_velocity FROM bsf JOIN field USING (step, voxel)",
    "workload_e3": f"{LABELS}, {ACCURACY.replace('FROM got f', 'FROM bubbles f')} FROM n",
    "workload_e4": f"{LABELS}, {TRAITS} SELECT step, bubble, voxels, round(aspect, 6) AS aspect FROM described WHERE aspect BETWEEN 0.5 AND 1.5 AND voxels BETWEEN 10 AND 60",
    "workload_e5": f"""{LABELS}, {TRAITS}, {edges()}, {BEST}, {traced(SEED)}, followed AS MATERIALIZED (SELECT t.*, voxels, xc FROM tracks t JOIN described USING (step, bubble)) SELECT track, step, bubble, voxels, round(dice, 9) AS dice, round({STEPPED}, 4) AS rise_velocity,
  coalesce(dice < {d(0.3)} OR (count(dice) OVER v >= 2 AND dice < round(avg(dice) OVER v - {d(2.0)} * stddev_pop(dice) OVER v, 12) - {d(1e-9)}), false) AS low_confidence
FROM followed WINDOW w AS (PARTITION BY track ORDER BY step), v AS (PARTITION BY track ORDER BY step ROWS BETWEEN 5 PRECEDING AND 1 PRECEDING)""",
    "workload_e6": f"{MOVING} SELECT track, step, voxels, round(change, 6) AS change, CASE WHEN change >= {d(0.5)} THEN 'merge' ELSE 'split' END AS event FROM moved WHERE change >= {d(0.5)} OR change <= {d(-0.33)}",
    "workload_e7": f"""{LABELS}, {TRAITS}, {edges()}, {BEST}, {traced('SELECT step, bubble FROM described WHERE step = 0 ORDER BY zc, bubble LIMIT 1', 0)}, one AS (SELECT step, volume, xc, {STEPPED} AS rise_velocity FROM tracks JOIN described USING (step, bubble) WINDOW w AS (ORDER BY step))
{" UNION ALL ".join(f"SELECT '{a}' AS row_trait, '{b}' AS col_trait, round(corr({a}, {b}), 6) AS r FROM one" for b, a in (("step", "volume"), ("step", "xc"), ("step", "rise_velocity"), ("volume", "xc"), ("volume", "rise_velocity"), ("xc", "rise_velocity")))}""",
    "workload_e8": f"""{SHAPES}, {TRAITS}, {edges()}, {BEST}, {traced('SELECT step, bubble FROM described WHERE step = 6', 6)}, followed AS (SELECT track, step, max(volume) AS v FROM tracks JOIN described USING (step, bubble) GROUP BY ALL)
SELECT CAST(t AS INT) AS step, k.track, round(v, 4) AS volume FROM range({SCENE_STEPS["shapes"]}) r(t) CROSS JOIN (SELECT DISTINCT track FROM tracks) k LEFT JOIN followed f ON f.track = k.track AND f.step = t""",
    "workload_e9": f"""{LABELS}, {MOTION.format(e=d(0.1), wake=d(3.0), above=d(1.0), side=d(-2.0), half=d(0.5), nx=d(float(NX)), nz=d(float(NZ)))},
moved_field AS MATERIALIZED (SELECT f.step, f.voxel, f.ix, f.iy, f.iz, s / n AS rise_velocity FROM field f LEFT JOIN (SELECT b.step, b.voxel, count(*) AS n, sum(coalesce(v_set, vx)) AS s FROM bed b LEFT JOIN motion m ON m.step = b.step AND m.voxel = b.voxel GROUP BY ALL) c USING (step, voxel)),
{around()}, {around("moved_field", "_w")}
{" UNION ALL ".join(f"SELECT '{k}' AS velocity, region, count(*) AS bubbles, round(avg(mean_rise), 5) AS mean_rise, round(avg(up_share), 5) AS up_share, round(avg(down_share), 5) AS down_share FROM around{t} GROUP BY region" for k, t in (("as given", ""), ("set", "_w")))}""",
    "workload_e10": f"""WITH RECURSIVE {bed("shapes")}, {target(BOXES["shapes"])}, {", ".join(parts_of(s) for s in (3, 4, 6))}, {TRUE_BUBBLES}
SELECT CAST(size AS INT) AS size, partition, small, count(*) AS bubbles, count(*) FILTER (recalled) AS recalled FROM ({" UNION ALL ".join(recalled(f"_{how[0]}{s}", s, how) for s in (3, 4, 6) for how in ("supervoxels", "blocks"))}) GROUP BY size, partition, small""",
    "workload_e11": f"""WITH RECURSIVE {run()}, seg AS MATERIALIZED ({" UNION ALL ".join(f"SELECT CAST(step + {1000 * i} AS INT) AS step, voxel, ix, iy, iz FROM bsf JOIN lattice USING (voxel) WHERE similarity >= {d(t)}" for i, t in enumerate(THRESHOLDS, 1))}), {reached("seg", "found")}, {kept()}
SELECT [{", ".join(map(d, THRESHOLDS))}][CAST(step // 1000 AS INT)] AS threshold, count(DISTINCT row(step, bubble)) AS bubbles, count(*) AS voxels FROM bubbles GROUP BY 1""",
    "workload_e12": " UNION ALL ".join(with_bins(n) for n in BINS),
    "workload_e18": f"{LABELS}, {edges()}, {BEST}, {traced(FIRST, 0)}, {LAYERS}",
    "workload_e19": f"""{SHAPES}, {TRUE_BUBBLES}, {edges()}, {edges(name="true_edges", bubbles="true_bubbles")}, {", ".join(f"ends{t} AS MATERIALIZED ({ENDS.format(b)}), boxes{t} AS MATERIALIZED ({BOX_LINKS.format('ends' + t)})" for t, b in (("_e", "bubbles"), ("_p", "true_bubbles")))}
{" UNION ALL ".join(f"SELECT '{name}' AS bubbles, 'boxes' AS links, count(*) AS n FROM boxes{t} UNION ALL SELECT '{name}', 'overlap', count(*) FROM {e} UNION ALL SELECT '{name}', 'boxes only', count(*) FROM boxes{t} b WHERE NOT EXISTS (SELECT 1 FROM {e} e WHERE e.step = b.step AND e.src = b.src AND e.dst = b.dst)" for name, t, e in (("extracted", "_e", "edges"), ("planted", "_p", "true_edges")))}""",
    "workload_e20": f"""WITH {BED}, {seeds()}, {", ".join(iteration(k) for k in range(1, 6))}, {global_rounds(8 * 2 * 8, 5)}, local_rounds AS ({" UNION ALL ".join(f"SELECT step, {k} AS iteration, count(*) FILTER (moved) AS changed, sum(tested) AS distances FROM labels_{k} GROUP BY step" for k in range(1, 6))})
SELECT 'local' AS method, CAST(iteration AS INT) AS iteration, CAST(sum(distances) AS BIGINT) AS distances FROM local_rounds r WHERE NOT EXISTS (SELECT 1 FROM local_rounds b WHERE b.step = r.step AND b.iteration < r.iteration AND b.changed = 0) GROUP BY iteration
UNION ALL SELECT 'global', iteration, CAST(sum(distances) AS BIGINT) FROM global_rounds GROUP BY iteration""",
}
#: The first bed's threshold, then all beds.
LINES_BED = f"WITH {BED}, {target(void_box(bed_grid()))}"
SQL["workload_e13"] = f"""WITH tuned AS MATERIALIZED (SELECT fixed FROM ({LINES_BED} SELECT (any_value(m0) + CAST(sum(density) AS DOUBLE) / count(*)) / {d(2.0)} AS fixed FROM field CROSS JOIN goal WHERE step = 0 AND (ix + {d(0.5)}) / {d(float(NX))} < {d(0.85)}))
{" UNION ALL ".join([compared("lines", (NX, NY, NZ)), *[compared("orders", n, ORDERS, {"x": (900.0, 500000.0), "y": (0.0, 5.0), "z": (0.0, 50.0)}) for n in ORDER_BINS]])}"""
