"""DuckDB SQL for the registered queries, on the same tables.

Common table expressions are built here once; each oracle selects from them.
"""

from __future__ import annotations

from ..functions.tails import ERFC
from ..operators.resampling import POISSON
from ..schema import FEATURES, PRIMARY, SEEDS
from ..sources.tables import BLOCK_ORDER, DEPTHS, LOOPS, OFFSETS, OUTLINES

NL = "chr(10)"
#: Page features and their tags, as in the query.
PAGE_FEATURES = (("LIST", "li"), ("LINKS", "a"), ("HEADINGS", "h1"), ("PARAGRAPHS", "p"))


def _hex(e: str) -> str:
    return f"(('0x' || substr(md5({e}), 1, 8))::UBIGINT)::BIGINT"


def _loop(points) -> str:
    return f" || {NL} || ".join(f"'{'seg' if i else 'pen'} ' || (s * {x}) || ' ' || (s * {y})" for i, (x, y) in enumerate(points))


def _phi(p: str) -> str:
    num = lambda r, g=1: f"list_transform(regexp_extract_all({p}, '{r}', {g}), lambda v: v::INT)"
    depth = f"list_max({num('raise ([0-9]{1,8})')})"
    width = f"list_max(list_concat(list_concat({num('(?:pen|seg) ([0-9]{1,8}) [0-9]{1,8}')}, {num('(?:pen|seg) [0-9]{1,8} ([0-9]{1,8})')}), list_transform({num('disc ([0-9]{1,8})')}, lambda v: 2 * v)))"
    return (
        f"(CASE WHEN regexp_matches({p}, 'disc [0-9]+') THEN 1 ELSE 0 END + CASE WHEN regexp_matches({p}, '(seg [0-9]+ [0-9]+\\n){{4,}}shut') THEN 2 ELSE 0 END"
        f" + CASE WHEN coalesce(10 * {depth} < 3 * {width}, false) THEN 4 ELSE 0 END + CASE WHEN coalesce({depth} > 2 * {width}, false) THEN 8 ELSE 0 END"
        f" + CASE WHEN len(regexp_extract_all({p}, 'raise [0-9]+')) > 1 THEN 16 ELSE 0 END)::INT"
    )


def _profile(b: str) -> str:
    return "concat_ws('+', " + ", ".join(f"CASE WHEN ({b} & {1 << i}) <> 0 THEN '{n}' END" for i, n in enumerate(PRIMARY)) + ")"


def _psi(n: str, source: str) -> str:
    """CTEs ending in {n}_psi(program, ok, psi5) for the distinct programs of a source."""
    num = lambda e: f"CASE WHEN regexp_full_match({e}, '[0-9]{{1,8}}') THEN ({e})::BIGINT END"
    # a label reaches all blocks of a solid in as many rounds as it has blocks, less one
    rounds = "\n".join(f"{n}_l{i + 1} AS (SELECT s.program, s.b, least(any_value(s.l), coalesce(min(o.l), any_value(s.l))) AS l FROM {n}_l{i} s LEFT JOIN {n}_nb k ON k.program = s.program AND k.a = s.b LEFT JOIN {n}_l{i} o ON o.program = k.program AND o.b = k.c GROUP BY s.program, s.b)," for i in range(5))
    return f"""
{n}_st AS (SELECT program, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS s FROM (SELECT program, string_split(program, {NL}) AS l FROM (SELECT DISTINCT program FROM {source}))),
{n}_bk AS (SELECT program, i, string_split(s, ' ') AS w, coalesce(sum(CASE WHEN split_part(s, ' ', 1) = 'raise' THEN 1 ELSE 0 END) OVER (PARTITION BY program ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::INT AS b FROM {n}_st),
{n}_g AS (SELECT program, b, list(w ORDER BY i) AS ss FROM {n}_bk GROUP BY 1, 2),
{n}_k AS (SELECT program, b, ss[1] AS f, ss[len(ss)] AS l, ss[2:len(ss) - 1] AS mid, len(ss) AS n FROM {n}_g),
{n}_h AS (SELECT *, mid[1:len(mid) - 1] AS lp, n >= 3 AND f[1] = 'sheet' AND len(f) = 2 AND l[1] = 'raise' AND len(l) = 2 AS framed FROM {n}_k),
{n}_s AS (SELECT program, b, lp, {num('f[2]')} AS x, {num('mid[1][2]')} AS r, {num('l[2]')} AS d,
  CASE WHEN coalesce(framed AND len(mid) = 1 AND mid[1][1] = 'disc' AND len(mid[1]) = 2, false) THEN 'disc'
       WHEN coalesce(framed AND len(mid) >= 4 AND mid[1][1] = 'pen' AND len(mid[len(mid)]) = 1 AND mid[len(mid)][1] = 'shut' AND len(list_filter(lp[2:], lambda e: e[1] <> 'seg')) = 0
            AND len(list_filter(lp, lambda e: NOT (len(e) = 3 AND regexp_full_match(coalesce(e[2], ''), '[0-9]{{1,8}}') AND regexp_full_match(coalesce(e[3], ''), '[0-9]{{1,8}}')))) = 0, false) THEN 'poly' ELSE 'bad' END AS shape FROM {n}_h),
{n}_u AS (SELECT program, b, unnest(range(0, len(lp))) AS j, len(lp) AS m, unnest(list_transform(lp, lambda e: e[2]::BIGINT)) AS px, unnest(list_transform(lp, lambda e: e[3]::BIGINT)) AS py FROM {n}_s WHERE shape = 'poly'),
{n}_e AS (SELECT p.program, p.b, p.j, p.px, p.py, q.px AS qx, q.py AS qy, o.px AS ox, o.py AS oy FROM {n}_u p JOIN {n}_u q ON p.program = q.program AND p.b = q.b AND q.j = (p.j + 1) % p.m JOIN {n}_u o ON p.program = o.program AND p.b = o.b AND o.j = (p.j + p.m - 1) % p.m),
{n}_a AS (SELECT program, b, min(px) AS x0, max(px) AS x1, min(py) AS y0, max(py) AS y1, sum(px * qy - qx * py) AS area, count(*) FILTER ((px - ox) * (qy - oy) - (py - oy) * (qx - ox) <> 0) AS sides FROM {n}_e GROUP BY 1, 2),
{n}_c AS (SELECT DISTINCT e.program FROM {n}_e e JOIN {n}_e g ON e.program = g.program AND e.b = g.b AND e.j < g.j WHERE
  sign((e.qx - e.px) * (g.py - e.py) - (e.qy - e.py) * (g.px - e.px)) * sign((e.qx - e.px) * (g.qy - e.py) - (e.qy - e.py) * (g.qx - e.px)) < 0
  AND sign((g.qx - g.px) * (e.py - g.py) - (g.qy - g.py) * (e.px - g.px)) * sign((g.qx - g.px) * (e.qy - g.py) - (g.qy - g.py) * (e.qx - g.px)) < 0),
{n}_b AS MATERIALIZED (SELECT s.program, s.b, shape, d, x, r, x + CASE WHEN shape = 'disc' THEN 0 ELSE a.x0 END AS x0, x + CASE WHEN shape = 'disc' THEN 2 * r ELSE a.x1 END AS x1, CASE WHEN shape = 'disc' THEN 0 ELSE a.y0 END AS y0, CASE WHEN shape = 'disc' THEN 2 * r ELSE a.y1 END AS y1, coalesce(sides, 0) AS sides,
  NOT (shape = 'bad' OR x IS NULL OR d IS NULL OR (shape = 'disc' AND r IS NULL)) AND NOT coalesce(d <= 0 OR (shape = 'disc' AND r <= 0) OR (shape = 'poly' AND area = 0), false) AS good FROM {n}_s s LEFT JOIN {n}_a a ON s.program = a.program AND s.b = a.b),
{n}_cd AS (SELECT s.program, s.b AS a, t.b AS c, s.shape AS sa, t.shape AS sc, s.x AS xa, t.x AS xc, s.r AS ra, t.r AS rc FROM {n}_b s JOIN {n}_b t ON s.program = t.program AND s.b < t.b AND s.good AND t.good AND s.x0 < t.x1 AND t.x0 < s.x1 AND s.y0 < t.y1 AND t.y0 < s.y1),
{n}_ax AS (SELECT k.program, a, c, e.qy - e.py AS nx, e.px - e.qx AS ny FROM {n}_cd k JOIN {n}_e e ON e.program = k.program AND (e.b = k.a OR e.b = k.c)
  UNION SELECT k.program, a, c, CASE WHEN sa = 'disc' THEN xa + ra - xc ELSE xc + rc - xa END - e.px, CASE WHEN sa = 'disc' THEN ra ELSE rc END - e.py FROM {n}_cd k JOIN {n}_e e ON e.program = k.program AND sa <> sc AND e.b = CASE WHEN sa = 'disc' THEN c ELSE a END),
{n}_pr AS (SELECT x.program, x.a, x.c, nx, ny, e.b, min((s.x + e.px) * nx + e.py * ny) AS lo, max((s.x + e.px) * nx + e.py * ny) AS hi FROM {n}_ax x JOIN {n}_e e ON e.program = x.program AND (e.b = x.a OR e.b = x.c) JOIN {n}_b s ON s.program = e.program AND s.b = e.b WHERE nx <> 0 OR ny <> 0 GROUP BY ALL),
{n}_sp AS (SELECT p.program, p.a, p.c FROM {n}_pr p JOIN {n}_pr q ON p.program = q.program AND p.a = q.a AND p.c = q.c AND p.nx = q.nx AND p.ny = q.ny AND p.b = p.a AND q.b = q.c WHERE p.hi <= q.lo OR q.hi <= p.lo
  UNION SELECT p.program, p.a, p.c FROM {n}_pr p JOIN {n}_b d ON d.program = p.program AND d.b IN (p.a, p.c) AND d.b <> p.b AND d.shape = 'disc'
    WHERE greatest(p.lo - ((d.x + d.r) * nx + d.r * ny), (d.x + d.r) * nx + d.r * ny - p.hi) >= 0 AND greatest(p.lo - ((d.x + d.r) * nx + d.r * ny), (d.x + d.r) * nx + d.r * ny - p.hi)::DOUBLE ** 2 >= d.r::DOUBLE ** 2 * (nx::DOUBLE ** 2 + ny::DOUBLE ** 2)),
{n}_ov AS (SELECT program, a, c FROM {n}_cd k WHERE CASE WHEN sa = 'disc' AND sc = 'disc' THEN (xa + ra - xc - rc)::DOUBLE ** 2 + (ra - rc)::DOUBLE ** 2 < (ra + rc)::DOUBLE ** 2 ELSE NOT EXISTS (SELECT 1 FROM {n}_sp z WHERE z.program = k.program AND z.a = k.a AND z.c = k.c) END),
{n}_nb AS (SELECT program, a, c FROM {n}_ov UNION ALL SELECT program, c, a FROM {n}_ov),
{n}_l0 AS (SELECT program, b, b AS l FROM {n}_b),
{rounds}
{n}_so AS (SELECT program, count(DISTINCT l) AS solids FROM {n}_l5 GROUP BY program),
{n}_v AS (SELECT n.program, bool_and(good) AND NOT bool_or(c.program IS NOT NULL) AS ok, bool_or(shape = 'disc') AS circle, max(sides) AS sides, max(d) AS dz, greatest(max(x1) - min(x0), max(y1) - min(y0)) AS wide, any_value(solids) AS solids FROM {n}_b n JOIN {n}_so o ON n.program = o.program LEFT JOIN {n}_c c ON n.program = c.program GROUP BY 1),
{n}_psi AS MATERIALIZED (SELECT program, ok, CASE WHEN ok THEN (CASE WHEN circle THEN 1 ELSE 0 END + CASE WHEN sides >= 5 THEN 2 ELSE 0 END + CASE WHEN 10 * dz < 3 * wide THEN 4 ELSE 0 END + CASE WHEN dz > 2 * wide THEN 8 ELSE 0 END + CASE WHEN solids > 1 THEN 16 ELSE 0 END) ELSE 0 END::INT AS psi5 FROM {n}_v)"""


_BODY = "CASE edges WHEN 0 THEN 'disc ' || (s * 5) " + " ".join(f"WHEN {n} THEN {_loop(p)} || CASE WHEN closed THEN {NL} || 'shut' ELSE '' END" for n, p in LOOPS.items()) + " END"
_ROUNDS = 6
_ALLOC = ",\n".join(
    ["al0 AS (SELECT profile, pool, NULL::BIGINT AS pin FROM counts)"]
    + [f"al{i + 1} AS (SELECT profile, pool, coalesce(pin, CASE WHEN pool * ((SELECT (least(400, (SELECT sum(pool) FROM counts)) - coalesce(sum(pin), 0))::DOUBLE / sum(pool) FILTER (pin IS NULL) FROM al{i})) < 15 THEN least(15, pool) END) AS pin FROM al{i})" for i in range(_ROUNDS)]
)
_GIVEN = ",\n".join(
    f"rk{s} AS (SELECT program_id, intent5, row_number() OVER (ORDER BY md5('R{s}:' || program_id), program_id) - 1 AS r, count(*) OVER () AS n FROM train),\n"
    f"gv{s} AS (SELECT a.program_id, a.intent5 AS own, b.intent5 AS given FROM rk{s} a JOIN rk{s} b ON b.r = (a.r + 1) % a.n)"
    for s in SEEDS
)
_CELLS = "(VALUES " + ", ".join(f"('{m}', '{f}', {s})" for s in SEEDS for m, f in (("U", "none"), ("M", "text"), ("M", "token"), ("R", "text"))) + ") c(model, form, seed)"
_H = "CASE model WHEN 'U' THEN -1 WHEN 'M' THEN intent5 ELSE CASE seed WHEN 0 THEN g0 WHEN 1 THEN g1 ELSE g2 END END"
_ARMS = "(VALUES ('U','none','uncond'),('M','text','correct'),('M','text','wrong'),('M','text','masked'),('M','token','correct'),('M','token','wrong'),('M','token','masked'),('R','text','correct'),('R','text','wrong')) m(model, form, arm)"

PROGRAMS = f"""
blk AS (SELECT l_orderkey, l_returnflag, k, edges, w, (w // 10) * kk AS d, CASE WHEN k = 1 THEN 0 ELSE x END AS x, closed, w // 10 AS s FROM (
  SELECT l_orderkey, l_returnflag, row_number() OVER (PARTITION BY l_orderkey, l_returnflag ORDER BY {', '.join(BLOCK_ORDER)}) AS k,
    CASE split_part(p_type, ' ', 1) {' '.join(f"WHEN '{k}' THEN {v}" for k, v in OUTLINES.items())} ELSE 4 END AS edges,
    ((floor((l_quantity - 1) / 10) + 1) * 10)::INT AS w, {list(DEPTHS)}[(round(l_discount * 100) + 1)::INT] AS kk, {list(OFFSETS)}[(l_suppkey % 4 + 1)::INT] AS x, round(l_tax * 100) <> 8 AS closed
  FROM lineitem JOIN part ON l_partkey = p_partkey) WHERE k <= 3),
raw AS (SELECT l_orderkey || '-' || l_returnflag AS program_id, l_orderkey, count(*)::INT AS n_blocks, string_agg('sheet ' || x || {NL} || {_BODY} || {NL} || 'raise ' || d, {NL} ORDER BY k) AS program FROM blk GROUP BY l_orderkey, l_returnflag),
bits AS (SELECT program, {_phi('program')} AS intent5 FROM (SELECT DISTINCT program FROM raw)),
prog AS MATERIALIZED (SELECT program_id, l_orderkey, n_blocks, program, sha256(program) AS program_sha, CASE WHEN {_hex('l_orderkey::VARCHAR')} % 10 < 8 THEN 'train' ELSE 'held' END AS split, intent5, (intent5 & 15)::INT AS intent4, {_profile('intent5')} AS profile,
  regexp_replace(regexp_replace(lower(program), 'sheet [0-9]+', 'sheet', 'g'), '[ \t]+', ' ', 'g') AS loose FROM raw JOIN bits USING (program))"""

#: CTEs from counts(profile, pool) to quota(profile, quota).
QUOTA = f"""{_ALLOC},
rate AS (SELECT (least(400, (SELECT sum(pool) FROM counts)) - coalesce(sum(pin), 0)) AS left_, (least(400, (SELECT sum(pool) FROM counts)) - coalesce(sum(pin), 0))::DOUBLE / sum(pool) FILTER (pin IS NULL) AS r FROM al{_ROUNDS}),
fl AS (SELECT profile, pool, pin, floor(pool * r)::BIGINT AS whole, pool * r - floor(pool * r) AS frac, left_ FROM al{_ROUNDS}, rate),
quota AS (SELECT profile, coalesce(pin, whole + CASE WHEN row_number() OVER (PARTITION BY pin IS NULL ORDER BY frac DESC, profile) <= left_ - sum(CASE WHEN pin IS NULL THEN whole END) OVER () THEN 1 ELSE 0 END) AS quota FROM fl)"""


def _cut(pct: int) -> str:
    return f"substr(program, 1, floor(length(program) * {pct} / 100)::INT)"


def _sample(pct: int = 40) -> str:
    return f"""{PROGRAMS},
clean AS (SELECT * FROM prog h WHERE split = 'held' AND NOT EXISTS (SELECT 1 FROM prog t WHERE t.split = 'train' AND t.program = h.program) AND NOT EXISTS (SELECT 1 FROM prog t WHERE t.split = 'train' AND t.loose = h.loose)),
pool AS MATERIALIZED (SELECT * FROM clean WHERE program_id IN (SELECT min(program_id) FROM clean GROUP BY program) AND intent4 > 0),
counts AS (SELECT profile, count(*) AS pool FROM pool GROUP BY 1),
{QUOTA},
sample AS MATERIALIZED (SELECT p.*, {_cut(pct)} AS prefix, sha256({_cut(pct)}) AS prefix_sha FROM (
  SELECT *, row_number() OVER (PARTITION BY profile ORDER BY md5('20260805:' || program_id), program_id) AS rn FROM pool) p JOIN quota USING (profile) WHERE rn <= quota)"""


SAMPLE = _sample()
EARLIER = f"{PROGRAMS}, sample AS MATERIALIZED (SELECT *, {_cut(40)} AS prefix, sha256({_cut(40)}) AS prefix_sha FROM (SELECT * FROM prog WHERE split = 'held' AND intent4 > 0 ORDER BY md5('initial:' || program_id), program_id LIMIT 100))"

PLAN = """
hs AS (SELECT max(c) AS g, sum(c)::BIGINT AS n FROM (SELECT count(*) AS c FROM sample GROUP BY intent5)),
hr AS (SELECT program_id, intent5, row_number() OVER (ORDER BY intent5, md5('plan:' || program_id), program_id) - 1 AS r FROM sample),
plan AS MATERIALIZED (SELECT a.program_id, a.intent5 AS own, b.intent5 AS given FROM hr a, hs, hr b WHERE b.r = (a.r + g) % n)"""

TRAIN = f"""
train AS MATERIALIZED (SELECT program_id, program, intent5 FROM prog WHERE split = 'train' AND intent5 > 0),
{_GIVEN},
seen AS MATERIALIZED (SELECT t.program_id, t.program, t.intent5, gv0.given AS g0, gv1.given AS g1, gv2.given AS g2 FROM train t JOIN gv0 USING (program_id) JOIN gv1 USING (program_id) JOIN gv2 USING (program_id))"""


def _stem(e: str) -> str:
    return f"array_to_string(string_split({e}, {NL})[1:2], {NL})"


def _scores(sample: str, arms: str = _ARMS, other: str = "0") -> str:
    """CTEs ending in sc, the score rows of a sample; ``other`` is the header of arms that are neither correct nor wrong."""
    return f"""{sample}, {PLAN}, {TRAIN},
pre AS (SELECT DISTINCT prefix FROM sample),
hit AS (SELECT seen.*, prefix FROM seen JOIN pre ON starts_with(program, prefix)),
mh AS MATERIALIZED (SELECT model, form, seed, {_H} AS h, md5(seed || ':' || form || ':' || program_id) AS key, program, prefix FROM hit, {_CELLS} WHERE {_hex("seed || ':' || form || ':' || program_id")} % 10 < 8),
one AS (SELECT model, form, seed, h, prefix, arg_min(program, key) AS p1 FROM mh GROUP BY ALL),
two AS (SELECT model, form, seed, prefix, arg_min(program, key) AS p2 FROM mh GROUP BY ALL),
stems AS (SELECT DISTINCT {_stem('prefix')} AS stem FROM sample),
sh AS (SELECT seen.*, stem FROM (SELECT *, {_stem('program')} AS stem FROM seen) seen JOIN stems USING (stem)),
three AS (SELECT model, form, seed, stem, arg_min(program, (length(program), md5(seed || ':' || form || ':' || program_id))) AS p3 FROM sh, {_CELLS} WHERE {_hex("seed || ':' || form || ':' || program_id")} % 10 < 8 GROUP BY ALL),
jobs AS (SELECT s.program_id, s.prefix, {_stem('s.prefix')} AS stem, m.model, m.form, m.arm, d.seed, CASE WHEN m.model = 'U' THEN -1 WHEN m.arm = 'correct' THEN s.intent5 WHEN m.arm = 'wrong' THEN plan.given ELSE {other} END AS h FROM sample s JOIN plan USING (program_id), {arms}, (VALUES (0), (1), (2)) d(seed)),
gen AS MATERIALIZED (SELECT j.*, CASE WHEN j.h <> 0 AND p1 IS NOT NULL THEN 1 WHEN j.h <> 0 AND p2 IS NOT NULL THEN 2 ELSE 3 END AS level,
  j.prefix || substr(CASE WHEN j.h <> 0 AND p1 IS NOT NULL THEN p1 WHEN j.h <> 0 AND p2 IS NOT NULL THEN p2 ELSE coalesce(p3, '') END, length(j.prefix) + 1) AS program
  FROM jobs j LEFT JOIN one ON j.model = one.model AND j.form = one.form AND j.seed = one.seed AND j.h = one.h AND j.prefix = one.prefix LEFT JOIN two ON j.model = two.model AND j.form = two.form AND j.seed = two.seed AND j.prefix = two.prefix LEFT JOIN three ON j.model = three.model AND j.form = three.form AND j.seed = three.seed AND j.stem = three.stem),
{_psi('gn', 'gen')},
gphi AS (SELECT program, {_phi('program')} AS phi5 FROM (SELECT DISTINCT program FROM gen)),
sc AS MATERIALIZED (SELECT g.*, ok, psi5, phi5, s.intent4, s.intent5, s.profile, s.prefix_sha, (6 * bit_count(s.intent4 & psi5) / bit_count(s.intent4))::INT AS adh6, (6 * bit_count(s.intent4 & phi5) / bit_count(s.intent4))::INT AS rec6, CASE WHEN ok THEN (6 * bit_count(s.intent4 & phi5) / bit_count(s.intent4))::INT ELSE 0 END AS gated6
  FROM gen g JOIN gn_psi USING (program) JOIN gphi USING (program) JOIN sample s ON g.program_id = s.program_id)"""


SCORES = _scores(SAMPLE)
REFS = f"{SAMPLE}, {_psi('rf', 'sample')}, refs AS (SELECT s.*, ok, psi5, (6 * bit_count(intent4 & psi5) / bit_count(intent4))::INT AS adh6 FROM sample s JOIN rf_psi USING (program))"


def _diff(arm: str) -> str:
    """CTE x(form, seed, program_id, prefix_sha, profile, d, ok)."""
    return f"x AS (SELECT a.form, a.seed, a.program_id, a.prefix_sha, a.profile, (a.adh6 - b.adh6) / 6.0::DOUBLE AS d, a.ok AND b.ok AS ok FROM sc a JOIN sc b ON b.model = 'U' AND a.seed = b.seed AND a.program_id = b.program_id WHERE a.model = 'M' AND a.arm = '{arm}')"


INTER = """x AS (SELECT seed, program_id, prefix_sha, any_value(profile) AS profile, (max(adh6) FILTER (model = 'M' AND arm = 'correct') - max(adh6) FILTER (model = 'M' AND arm = 'wrong')) / 6.0::DOUBLE AS drop_m,
 (max(adh6) FILTER (model = 'R' AND arm = 'correct') - max(adh6) FILTER (model = 'R' AND arm = 'wrong')) / 6.0::DOUBLE AS drop_r, bool_and(ok) AS ok FROM sc WHERE form = 'text' AND arm IN ('correct', 'wrong') GROUP BY 1, 2, 3),
y AS (SELECT *, drop_m - drop_r AS d FROM x)"""


def _lnup(z: str) -> str:
    x = f"(abs({z}) / sqrt(2.0::DOUBLE))"
    t = f"(1.0 / (1.0 + 0.5 * {x}))"
    poly = "0.0::DOUBLE"
    for c in reversed(ERFC):
        poly = f"({poly} * {t} + ({c}))"
    return f"(ln({t}) - {x} * {x} + {poly} - ln(2.0::DOUBLE))"


def _p(z: str, alt: str) -> str:
    sf = lambda e: f"CASE WHEN {e} >= 0 THEN exp({_lnup(e)}) ELSE 1.0 - exp({_lnup(e)}) END"
    return sf(z) if alt == "greater" else sf(f"(-{z})") if alt == "less" else f"2.0 * exp({_lnup(z)})"


def _LF(e: str) -> str:
    return f"lgamma({e} + 1)"


def _wilcoxon(src: str, cell: str, alt: str, zeros: str = "pratt", tag: str = "t") -> str:
    """CTEs ending in {tag}(cell, n, n_zero, n_pos, n_neg, mean_d, t_plus, z, p)."""
    r = "1.0::DOUBLE" if zeros == "sign" else f"(coalesce(sum(c) OVER (PARTITION BY {cell} ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + (c + 1) / 2.0::DOUBLE)"
    where = "WHERE v > 0" if zeros == "drop" else ""
    z2 = "1" if zeros == "split" else "0"
    return f"""
{tag}_v AS (SELECT {cell}, round(abs(d), 12) AS v, count(*) FILTER (d > 0) AS pos, count(*) FILTER (d < 0) AS neg, count(*) AS c FROM {src} GROUP BY ALL),
{tag}_r AS (SELECT *, {r} AS r FROM {tag}_v {where}),
{tag}_a AS (SELECT {cell}, sum(pos * r) + {z2} * sum(CASE WHEN v = 0 THEN c * r ELSE 0 END) / 2 AS t_plus, (sum(CASE WHEN v > 0 THEN c * r ELSE 0 END) + {z2} * sum(CASE WHEN v = 0 THEN c * r ELSE 0 END)) / 2 AS mu, (sum(CASE WHEN v > 0 THEN c * r * r ELSE 0 END) + {z2} * sum(CASE WHEN v = 0 THEN c * r * r ELSE 0 END)) / 4 AS var, sum(CASE WHEN v > 0 THEN c * r * r ELSE 0 END) AS sr2 FROM {tag}_r GROUP BY {cell}),
{tag}_n AS (SELECT {cell}, sum(c)::BIGINT AS n, sum(CASE WHEN v = 0 THEN c ELSE 0 END)::BIGINT AS n_zero, sum(pos)::BIGINT AS n_pos, sum(neg)::BIGINT AS n_neg, sum(v * (pos - neg)) / sum(c) AS mean_d FROM {tag}_v GROUP BY {cell}),
{tag}_z AS (SELECT n.*, t_plus, CASE WHEN sr2 > 0 THEN (t_plus - mu) / sqrt(var) END AS z FROM {tag}_n n LEFT JOIN {tag}_a a USING ({cell})),
{tag} AS (SELECT *, {_p('z', alt)} AS p FROM {tag}_z)"""


def _test(pre: str, src: str, cell: str, alt: str) -> str:
    want = "mean_d > 0" if alt == "greater" else "mean_d < 0" if alt == "less" else "mean_d <> 0"
    return f"WITH {pre}, {_wilcoxon(src, cell, alt)} SELECT {cell}, n, n_zero, n_pos, n_neg, round(mean_d, 9) AS mean_d, round(t_plus, 9) AS t_plus, round(z, 9) AS z, round(log10(p), 6) AS p, coalesce(p < 0.05, false) AS significant, {want} AS in_direction FROM t"


def _pick(tag: str, n: int) -> str:
    return f"({_hex(f"'{tag}:' || program_id")} % {n})::INT"


def _corrupt(k: int) -> str:
    first = _pick("c1", 4)
    mask = f"(1 << {first})" + (f" | (1 << (({first} + 1 + {_pick('c2', 3)}) % 4))" if k > 1 else "")
    x = f"xor(intent5, {mask})"
    return f"(CASE WHEN ({x} & 12) = 12 AND (intent5 & 4) <> 0 THEN {x} & ~4 WHEN ({x} & 12) = 12 THEN {x} & ~8 ELSE {x} END)"


_RANDOM = f"(CASE bit_count(intent4) WHEN 1 THEN [1, 2, 4, 8][{_pick('r1', 4)} + 1] WHEN 2 THEN [3, 5, 9, 6, 10][{_pick('r2', 5)} + 1] WHEN 0 THEN 0 ELSE [7, 11][{_pick('r3', 2)} + 1] END)"


def _render(bits: str, form: str) -> str:
    words = ", ".join(f"CASE WHEN ({bits} & {1 << b}) <> 0 THEN '{w if form == 'text' else f'<{n}>'}' END" for n, b, _, w in FEATURES)
    return f"CASE WHEN coalesce({bits}, 0) = 0 THEN '' ELSE " + (f"'# wants: ' || concat_ws(', ', {words})" if form == "text" else f"concat_ws(' ', '<WANT>', {words}, '</WANT>')") + " END"


def _counts(tag: str, src: str, h: str) -> str:
    """CTEs ending in {tag}(h, prev2, prev1, next, n)."""
    return f"""{tag}_s AS (SELECT {h} AS h, list_concat(['^', '^'], string_split(program, {NL}), ['']) AS s FROM {src}), {tag}_i AS (SELECT h, s, unnest(range(1, len(s) - 1)) AS i FROM {tag}_s),
{tag} AS MATERIALIZED (SELECT h, s[i] AS prev2, s[i + 1] AS prev1, s[i + 2] AS next, count(*) AS n FROM {tag}_i GROUP BY ALL)"""


def _smoothed(tag: str, counts: str, asked: str) -> str:
    """CTEs ending in {tag}(asked's columns, p)."""
    out, p = [], f"(coalesce((SELECT sum(n) FROM {counts} c WHERE c.next = a.next), 0) + 0.5::DOUBLE) / ((SELECT sum(n) FROM {counts}) + 0.5::DOUBLE * ((SELECT count(DISTINCT next) FROM {counts}) + 1))"
    out.append(f"{tag}_0 AS (SELECT a.*, {p} AS p FROM {asked} a)")
    levels = (("prev1",), ("h", "prev1"), ("h", "prev2", "prev1"))
    for i, keys in enumerate(levels):
        k = ", ".join(keys)
        out.append(f"{tag}_c{i} AS (SELECT {k}, next, sum(n) AS c FROM {counts} GROUP BY ALL), {tag}_t{i} AS (SELECT {k}, sum(n) AS t FROM {counts} GROUP BY ALL)")
        out.append(f"{tag}_{i + 1} AS (SELECT a.* EXCLUDE (p), (coalesce(c, 0) + 0.5::DOUBLE * p) / (coalesce(t, 0) + 0.5::DOUBLE) AS p FROM {tag}_{i} a LEFT JOIN {tag}_c{i} USING ({k}, next) LEFT JOIN {tag}_t{i} USING ({k}))")
    out.append(f"{tag} AS MATERIALIZED (SELECT * FROM {tag}_{len(levels)})")
    return ", ".join(out)


def _greedy(tag: str, counts: str, heads: str) -> str:
    return f"""{tag}_o AS (SELECT h, prev2, prev1, arg_max(next, (n, next)) AS next FROM {counts} GROUP BY ALL),
{tag}_a AS (SELECT prev2, prev1, arg_max(next, (n, next)) AS other FROM (SELECT prev2, prev1, next, sum(n) AS n FROM {counts} GROUP BY ALL) GROUP BY ALL),
{tag} AS MATERIALIZED (SELECT hs.h, a.prev2, a.prev1, coalesce(o.next, a.other) AS next FROM {tag}_a a CROSS JOIN (SELECT DISTINCT h FROM {heads}) hs LEFT JOIN {tag}_o o ON o.h = hs.h AND o.prev2 = a.prev2 AND o.prev1 = a.prev1)"""


def _decode(tag: str, steps: str, counts: str, starts: str, begin: bool = True, cap: int = 24) -> str:
    """CTEs ending in {tag}(id, h, ..., completion, hit_cap, program): ``starts`` has id and h, and prefix or (prev2, prev1)."""
    pre = f"{tag}_b AS (SELECT *, '' AS head, prev1 AS p1, prev2 AS p2 FROM {starts})"
    if begin:
        fit = lambda i, keys: f"{tag}_f{i} AS (SELECT {', '.join([*keys, 'cut'])}, arg_max(next, (n, next)) AS f{i} FROM (SELECT {', '.join(f'w.{k}' for k in keys)}{', ' if keys else ''}w.cut, c.next, sum(c.n) AS n FROM (SELECT DISTINCT {', '.join([*keys, 'cut'])} FROM {tag}_c) w JOIN {counts} c ON {' AND '.join([*(f'w.{k} = c.{k}' for k in keys), 'c.next <> $$$$', 'starts_with(c.next, w.cut)'])} GROUP BY ALL) GROUP BY ALL)"
        pre = f"""{tag}_l AS (SELECT *, string_split(prefix, {NL}) AS l FROM {starts}), {tag}_w AS (SELECT * EXCLUDE (l), l[1:len(l) - 1] AS w, l[len(l)] AS cut FROM {tag}_l),
{tag}_c AS MATERIALIZED (SELECT *, CASE WHEN len(w) > 1 THEN w[len(w) - 1] ELSE '^' END AS prev2, CASE WHEN len(w) > 0 THEN w[len(w)] ELSE '^' END AS prev1 FROM {tag}_w),
{fit(0, ('h', 'prev2', 'prev1'))}, {fit(1, ('prev2', 'prev1'))}, {fit(2, ())},
{tag}_d AS (SELECT c.*, coalesce(f0, f1, f2, c.cut) AS one FROM {tag}_c c LEFT JOIN {tag}_f0 x ON c.h = x.h AND c.prev2 = x.prev2 AND c.prev1 = x.prev1 AND c.cut = x.cut LEFT JOIN {tag}_f1 y ON c.prev2 = y.prev2 AND c.prev1 = y.prev1 AND c.cut = y.cut LEFT JOIN {tag}_f2 z ON c.cut = z.cut),
{tag}_b AS MATERIALIZED (SELECT * EXCLUDE (w, cut, prev1, prev2, one), array_to_string(list_append(w, one), {NL}) AS head, one AS p1, prev1 AS p2 FROM {tag}_d)"""
    return f"""{pre},
{tag}_r AS (SELECT id, h, p2, p1, 0 AS k, []::VARCHAR[] AS made FROM {tag}_b UNION ALL
  SELECT r.id, r.h, r.p1, s.next, k + 1, CASE WHEN s.next = '' OR k >= {cap} THEN made ELSE list_append(made, s.next) END FROM {tag}_r r JOIN {steps} s ON s.h = r.h AND s.prev2 = r.p2 AND s.prev1 = r.p1 WHERE k <= {cap} AND (k = 0 OR r.p1 <> '')),
{tag}_e AS (SELECT id, arg_max(made, k) AS made, NOT (max(k) > 0 AND arg_max(p1, k) = '' AND max(k) <= {cap} + 1) AS hit_cap FROM {tag}_r GROUP BY id),
{tag} AS MATERIALIZED (SELECT b.*, array_to_string(made, {NL}) AS completion, hit_cap, CASE WHEN len(made) = 0 THEN head ELSE head || {NL} || array_to_string(made, {NL}) END AS program FROM {tag}_b b JOIN {tag}_e USING (id))"""


_ASKED = f"asked AS MATERIALIZED (SELECT s.program_id || ':' || m.model || ':' || m.arm AS id, s.program_id, m.model, m.arm, s.prefix, CASE WHEN m.arm = 'correct' THEN s.intent5 WHEN m.arm = 'wrong' THEN plan.given ELSE 0 END AS h FROM sample s JOIN plan USING (program_id), {_ARMS} WHERE m.form IN ('text', 'none'))"
DECODED = f"""{SAMPLE}, {PLAN}, {TRAIN}, {_ASKED},
{', '.join(f"{_counts('k' + m, 'seen', h)}, a{m} AS (SELECT * FROM asked WHERE model = '{m}'), {_greedy('g' + m, 'k' + m, 'a' + m)}, {_decode('d' + m, 'g' + m, 'k' + m, 'a' + m)}" for m, h in (('M', 'intent5'), ('R', 'g0'), ('U', '0')))},
dec AS MATERIALIZED (SELECT * FROM dM UNION ALL SELECT * FROM dR UNION ALL SELECT * FROM dU)"""


def _intervals(means: str, src: str) -> str:
    return f"SELECT form, unit, round(estimate, 9) AS estimate, round(lo, 9) AS lo, round(hi, 9) AS hi FROM (SELECT form, unit, quantile_cont(m, 0.025) AS lo, quantile_cont(m, 0.975) AS hi FROM {means} GROUP BY 1, 2) JOIN (SELECT form, 'pooled' AS unit, avg(d) AS estimate FROM {src} GROUP BY 1 UNION ALL SELECT form, seed::VARCHAR, avg(d) FROM {src} GROUP BY 1, 2) USING (form, unit)"


def _boot(pre: str, src: str = "y") -> str:
    return f"""WITH {pre}, bc AS (SELECT form, seed, d, row_number() OVER (PARTITION BY form, seed ORDER BY prefix_sha) - 1 AS i, count(*) OVER (PARTITION BY form, seed) AS k FROM {src}),
bd AS (SELECT form, b, s, CASE WHEN s < 1000 THEN {_hex("'S:' || b || ':' || s")} % 3 ELSE s - 1000 END AS seed, {_hex("'C:' || b || ':' || s || ':' || j")} % k AS i FROM (SELECT form, k, b, s, unnest(range(k)) AS j FROM (SELECT form, max(k) AS k FROM bc GROUP BY form), range(1, 201) bb(b), (VALUES (0), (1), (2), (1000), (1001), (1002)) ss(s))),
bm AS (SELECT bd.form, CASE WHEN s < 1000 THEN 'pooled' ELSE bd.seed::VARCHAR END AS unit, b, avg(d) AS m FROM bd JOIN bc ON bd.form = bc.form AND bd.seed = bc.seed AND bd.i = bc.i GROUP BY 1, 2, 3) {_intervals('bm', src)}"""


def _weight(key: str) -> str:
    u = f"(({_hex(key)} % 2147483648)::DOUBLE + 0.5) / 2147483648.0::DOUBLE"
    return f"len(list_filter({list(POISSON)}, lambda c: {u} > c))"


def _boot_poisson(pre: str, src: str = "y") -> str:
    return f"""WITH {pre}, bw AS (SELECT form, seed, b, d, {_weight("'P:' || b || ':' || seed || ':' || prefix_sha")} AS w, {_weight("'S:' || b || ':' || seed")} AS ws FROM {src}, range(1, 201) bb(b)),
bm AS (SELECT form, 'pooled' AS unit, b, sum(w * ws * d) / nullif(sum(w * ws), 0) AS m FROM bw GROUP BY 1, 3 HAVING sum(w * ws) > 0 UNION ALL SELECT form, seed::VARCHAR, b, sum(w * d) / nullif(sum(w), 0) FROM bw GROUP BY form, seed, b HAVING sum(w) > 0) {_intervals('bm', src)}"""


def _power(pre: str, src: str, unit: str) -> str:
    return f"""WITH {pre}, pw AS (SELECT form, seed, b, d, unnest(range({_weight(f"'W:' || b || ':' || {unit}")})) AS copy FROM {src}, range(1, 101) bb(b)), {_wilcoxon('pw', 'form, seed, b', 'less')}
SELECT form, round(avg((k >= 2)::INT), 9) AS power FROM (SELECT form, b, count(*) FILTER (p < 0.05) AS k FROM t GROUP BY 1, 2) GROUP BY form"""


CLUSTER = "y AS (SELECT form, seed, prefix_sha, sum(round(d * 6)) / (6 * count(*)) AS d, count(*) AS members FROM x GROUP BY ALL)"
_MEAN = "sum(adh6) / (6 * count(*))"
W = f"{SCORES}, {_diff('wrong')}"

_HALF = "1.959964::DOUBLE * sqrt(a / nullif(n_named, 0) * (1 - a / nullif(n_named, 0)) / nullif(n_named, 0) + c / nullif(n_unnamed, 0) * (1 - c / nullif(n_unnamed, 0)) / nullif(n_unnamed, 0))"

ORACLES = {
    "corpus_programs": f"WITH {PROGRAMS} SELECT program_id, n_blocks, program_sha, split FROM prog",
    "phi_bits": f"WITH {PROGRAMS} SELECT program_id, intent5, intent4, profile FROM prog",
    "psi_bits": f"WITH {PROGRAMS}, {_psi('pp', 'prog')} SELECT sha256(program) AS sha, ok, psi5, regexp_full_match(program, '((sheet|disc|raise) [0-9]+|(pen|seg) [0-9]+ [0-9]+|shut)(\\n((sheet|disc|raise) [0-9]+|(pen|seg) [0-9]+ [0-9]+|shut))*') AND regexp_matches(program, 'raise [0-9]+$') AS valid FROM pp_psi",
    "dedup_exact": f"WITH {PROGRAMS} SELECT min(program_id) AS program_id, program_sha FROM prog GROUP BY program_sha",
    "dedup_loose": f"WITH {PROGRAMS} SELECT min(program_id) AS program_id FROM prog GROUP BY loose",
    "dedup_key_report": f"WITH {PROGRAMS}, q AS (SELECT *, floor(length(program) * 40 / 100)::INT AS c FROM prog), k AS (SELECT 'source' AS key, l_orderkey::VARCHAR AS v FROM q UNION ALL SELECT 'program', program FROM q UNION ALL SELECT 'prefix', substr(program, 1, c) FROM q UNION ALL SELECT 'completion', substr(program, c + 1) FROM q), g AS (SELECT key, v, count(*) AS n FROM k GROUP BY ALL) SELECT key, count(*) FILTER (n > 1) AS clusters, sum(n - 1)::BIGINT AS redundant, max(n) AS largest FROM g GROUP BY key",
    "leak_filter": f"WITH {SAMPLE} SELECT program_id FROM clean",
    "contamination": "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "pool_agree": f"WITH {SAMPLE} SELECT count(*) AS \"both\", 0::BIGINT AS only_a, 0::BIGINT AS only_b FROM pool",
    "length_profile": f"WITH {PROGRAMS}, q AS (SELECT split, len(regexp_extract_all(program, '[ \\n]')) + 1 AS n FROM prog) SELECT split, count(*) AS n, round(avg(n), 9) AS mean_len, max(n)::INT AS max_len, round(quantile_cont(n, 0.95), 9) AS p95_len, round(avg((n <= 1024)::INT), 9) AS within_cap FROM q GROUP BY split",
    "profile_counts": f"WITH {SAMPLE} SELECT * FROM counts",
    "quota_draw": f"WITH {SAMPLE} SELECT program_id, profile, prefix_sha FROM sample",
    "natural_weights": f"WITH {SAMPLE} SELECT profile, pool, round(pool / (SELECT sum(pool) FROM counts), 9) AS weight FROM counts",
    "sample_facts": f"WITH {SAMPLE} SELECT count(*) AS n, round(avg(bit_count(intent4)), 9) AS mean_tags, round(avg(((intent4 & 8) <> 0)::INT), 9) AS tall_sample, count(DISTINCT profile) AS profiles, count(DISTINCT prefix_sha) AS distinct_inputs, (SELECT round(avg(((intent4 & 8) <> 0)::INT), 9) FROM pool) AS tall_pool FROM sample",
    "header_vocab": f"WITH {PROGRAMS}, t AS (SELECT unnest(list_concat(['<WANT>', '</WANT>'], list_filter([{', '.join(f'CASE WHEN (intent5 & {1 << b}) <> 0 THEN $${chr(60)}{n}{chr(62)}$$ END' for n, b, _, _ in FEATURES)}], lambda v: v IS NOT NULL))) AS token FROM prog WHERE intent5 > 0) SELECT token, count(*) AS n FROM t GROUP BY token",
    "derangement_plan": f"WITH {PROGRAMS}, {TRAIN} SELECT program_id, own, given FROM gv0",
    "wrong_headers": f"WITH {SAMPLE}, {PLAN} SELECT program_id, own, given FROM plan",
    "chance_match": f"WITH {PROGRAMS}, {TRAIN} SELECT count(*) AS n, round(avg((own = given)::INT), 9) AS matched, (SELECT round(sum(p * p), 9) FROM (SELECT count(*) / sum(count(*)) OVER () AS p FROM gv0 GROUP BY own)) AS expected FROM gv0",
    "marginal_identity": f"WITH {PROGRAMS}, {TRAIN} SELECT h, count(*) AS n FROM ((SELECT own AS h FROM gv0 EXCEPT ALL SELECT given FROM gv0) UNION ALL (SELECT given FROM gv0 EXCEPT ALL SELECT own FROM gv0)) GROUP BY h",
    "retrieved_header": "WITH p AS (SELECT a.vec_id, a.label AS own, b.label AS given, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS c FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0) SELECT vec_id, own, arg_min(given, (-c, other)) AS given, round(max(c), 6) AS cosine FROM p GROUP BY vec_id, own",
    "prefix_clusters": f"WITH {SAMPLE} SELECT prefix_sha, count(*) AS members FROM sample GROUP BY 1",
    "prefix_leakage": f"WITH {SAMPLE}, q AS (SELECT {_phi('prefix')} & intent5 AS b FROM sample) SELECT count(*) AS n, round(avg(((b & 15) <> 0)::INT), 9) AS leak4, round(avg((b <> 0)::INT), 9) AS leak5 FROM q",
    "cap_calibration": f"WITH {PROGRAMS}, q AS (SELECT len(string_split(substr(program, floor(length(program) * 40 / 100)::INT + 1), {NL})) AS n FROM prog WHERE split = 'train' ORDER BY md5('cap:' || program_id), program_id LIMIT 20) SELECT count(*) AS n, quantile_cont(n, 0.95) AS cap FROM q",
    "generations": f"WITH {SCORES} SELECT program_id, model, form, arm, seed, h, level, sha256(program) AS sha FROM gen",
    "score_rows": f"WITH {SCORES} SELECT program_id, model, form, arm, seed, ok, phi5, psi5, adh6, rec6, gated6 FROM sc",
    "detector_agreement": f"WITH {REFS}, c AS (SELECT feature, ok, (intent5 & bit) <> 0 AS t, (psi5 & bit) <> 0 AS s FROM refs, (VALUES {', '.join(f'($${n}$$, {1 << i})' for i, n in enumerate(PRIMARY))}) f(feature, bit)), r AS (SELECT *, 'all' AS rows FROM c UNION ALL SELECT *, 'runnable' FROM c WHERE ok) SELECT feature, rows, count(*) AS n, round(avg((t = s)::INT), 9) AS agree, count(*) FILTER (t AND s) AS \"both\", count(*) FILTER (t AND NOT s) AS text_only, count(*) FILTER (NOT t AND s) AS solid_only FROM r GROUP BY 1, 2",
    "reference_self_score": f"WITH {REFS} SELECT count(*) AS n, round({_MEAN}, 9) AS self_score, count(*) FILTER (adh6 = 6) AS \"full\", count(*) FILTER (adh6 > 0 AND adh6 < 6) AS partial, count(*) FILTER (adh6 = 0) AS \"none\", count(*) FILTER (NOT ok) AS not_running FROM refs",
    "multi_part": f"WITH {SCORES} SELECT model, form, arm, count(*) AS n, count(*) FILTER ((psi5 & 16) <> 0) AS realized FROM sc WHERE ok AND (intent5 & 16) <> 0 GROUP BY 1, 2, 3",
    "output_identity": f"WITH {SCORES}, p AS (SELECT model, form, seed, program_id, bool_and(ok) AS ok, max(psi5 & 15) FILTER (arm = 'correct') AS c, max(psi5 & 15) FILTER (arm = 'wrong') AS w FROM sc WHERE arm IN ('correct', 'wrong') GROUP BY ALL) SELECT model, form, seed, count(*) AS runnable, count(*) FILTER (c = w) AS same FROM p WHERE ok GROUP BY 1, 2, 3",
    "arm_levels": f"""WITH {SCORES}, s AS (SELECT model, form, arm, seed, count(*) AS n, count(DISTINCT prefix_sha) AS inputs, sum(adh6) / (6 * count(*)) AS adherence, sum(rec6) / (6 * count(*)) AS regex_recall, sum(gated6) / (6 * count(*)) AS gated_recall, avg(ok::INT) AS executability,
      sum(bit_count(intent4 & psi5)) AS h, sum(bit_count(psi5 & 15)) AS m, sum(bit_count(intent4)) AS w, avg(((psi5 & 15) = intent4)::INT) AS exact_set, avg(CASE WHEN ok THEN bit_count(psi5 & 15) END) AS features_per_runnable, avg(CASE WHEN ok AND (psi5 & 15) <> 0 THEN bit_count(psi5 & 15) END) AS features_given_any, avg(CASE WHEN ok THEN ((psi5 & 15) = 0)::INT END) AS runnable_without, avg(CASE WHEN ok THEN adh6 / 6.0::DOUBLE END) AS runnable_adherence FROM sc GROUP BY 1, 2, 3, 4)
      SELECT model, form, arm, sum(n)::BIGINT AS n, max(inputs) AS distinct_inputs, {', '.join(f'round(avg({e}), 9) AS {n}' for n, e in (('adherence', 'adherence'), ('regex_recall', 'regex_recall'), ('gated_recall', 'gated_recall'), ('executability', 'executability'), ('micro_precision', 'h / nullif(m, 0)'), ('micro_recall', 'h / w'), ('micro_f1', '2 * h / nullif(m + w, 0)'), ('exact_set', 'exact_set'), ('features_per_runnable', 'features_per_runnable'), ('features_given_any', 'features_given_any'), ('runnable_without', 'runnable_without'), ('runnable_adherence', 'runnable_adherence')))} FROM s GROUP BY 1, 2, 3""",
    "recovery": f"WITH {SCORES}, {_psi('rf', 'sample')} SELECT model, form, arm, count(*) AS n, round({_MEAN}, 9) AS adherence, round(avg((adh6 = 6)::INT), 9) AS \"full\" FROM sc WHERE program_id IN (SELECT program_id FROM sample JOIN rf_psi USING (program) WHERE NOT ok) GROUP BY 1, 2, 3",
    "paired_wilcoxon": _test(W, "x", "form, seed", "less"),
    "cluster_wilcoxon": _test(f"{W}, {CLUSTER}", "y", "form, seed", "less"),
    "joint_executable": _test(f"{W}, y AS (SELECT * FROM x WHERE ok)", "y", "form, seed", "less"),
    "masked_contrast": _test(f"{SCORES}, {_diff('masked')}", "x", "form, seed", "less"),
    "benefit": _test(f"{SCORES}, {_diff('correct')}", "x", "form, seed", "two-sided"),
    "zero_handling": f"WITH {W}, {', '.join(_wilcoxon('x', 'form, seed', 'less', z, 't' + z) for z in ('pratt', 'drop', 'split', 'sign'))} " + " UNION ALL ".join(f"SELECT '{z}' AS zeros, form, seed, round(t_plus, 9) AS t_plus, round(z, 9) AS z, round(log10(p), 6) AS p FROM t{z}" for z in ("pratt", "drop", "split", "sign")),
    "profile_reweighting": f"WITH {W}, p AS (SELECT form, profile, count(DISTINCT program_id) AS n, sum(round(d * 6)) / (6 * count(*)) AS effect FROM x GROUP BY 1, 2), q AS (SELECT p.*, pool / (SELECT sum(pool) FROM counts) AS weight FROM p JOIN counts USING (profile)) SELECT form, round(avg(effect) FILTER (n >= 15), 9) AS guardrail, round(avg(effect), 9) AS equal_all, round(sum(effect * weight) / sum(weight), 9) AS \"natural\" FROM q GROUP BY form",
    "dissociation": f"WITH {SCORES}, {INTER}, {_wilcoxon('y', 'seed', 'greater')}, m AS (SELECT seed, avg(drop_m) AS drop_m, avg(drop_r) AS drop_r, count(*) FILTER (ok) AS n_joint, avg(d) FILTER (ok) AS joint FROM y GROUP BY seed) SELECT seed, n, n - n_zero AS nonzero, n - n_zero < 0.15 * n AS flagged, round(mean_d, 9) AS interaction, round(z, 9) AS z, round(log10(p), 6) AS p, coalesce(p < 0.05, false) AS significant, mean_d > 0 AS in_direction, round(drop_m, 9) AS drop_m, round(drop_r, 9) AS drop_r, n_joint, round(joint, 9) AS joint FROM t JOIN m USING (seed)",
    "competence_gate": f"WITH {SCORES}, r AS (SELECT seed, sum(adh6) FILTER (arm = 'correct') / (6 * count(*) FILTER (arm = 'correct')) AS c, sum(adh6) FILTER (arm = 'wrong') / (6 * count(*) FILTER (arm = 'wrong')) AS w FROM sc WHERE model = 'R' GROUP BY seed), e AS (SELECT avg(ok::INT) FILTER (model = 'R') AS a, avg(ok::INT) FILTER (model = 'U') AS b FROM sc), k AS (SELECT count(*) FILTER (c >= 0.3 AND w >= 0.3) AS seeds_ok FROM r) SELECT seeds_ok, round(a, 9) AS exec_r, round(b, 9) AS exec_base, seeds_ok >= 2 AND a >= b - 0.1 AS passed FROM k, e",
    "neither_named": f"WITH {SCORES}, f AS (SELECT w.model, w.form, feature, (w.psi5 & bit) <> 0 AS r, (u.psi5 & bit) <> 0 AS b FROM sc w JOIN sc u ON u.model = 'U' AND u.seed = w.seed AND u.program_id = w.program_id, (VALUES {', '.join(f'($${n}$$, {1 << i})' for i, n in enumerate(PRIMARY))}) f(feature, bit) WHERE w.arm = 'wrong' AND (w.h & bit) = 0 AND (w.intent4 & bit) = 0) SELECT model, form, feature, count(*) AS n, round(avg(r::INT), 9) AS rate, round(avg(b::INT), 9) AS base_rate FROM f GROUP BY 1, 2, 3",
    "per_profile": f"WITH {SCORES}, t AS (SELECT profile, count(DISTINCT program_id) AS n, {', '.join(f'avg(adh6 / 6.0::DOUBLE) FILTER (model = $${m}$$ AND form = $${f}$$ AND arm = $${a}$$) AS {k}' for k, m, f, a in (('baseline', 'U', 'none', 'uncond'), ('m_correct', 'M', 'text', 'correct'), ('m_wrong', 'M', 'text', 'wrong'), ('r_correct', 'R', 'text', 'correct'), ('r_wrong', 'R', 'text', 'wrong')))} FROM sc GROUP BY profile) SELECT profile, n, {', '.join(f'round({k}, 9) AS {k}' for k in ('baseline', 'm_correct', 'm_wrong', 'r_correct', 'r_wrong'))}, round(m_wrong - baseline, 9) AS wrong_minus_base, round((m_correct - m_wrong) - (r_correct - r_wrong), 9) AS interaction FROM t",
    "control_offset": f"WITH {SCORES}, b AS (SELECT seed, {_MEAN} AS base FROM sc WHERE model = 'U' GROUP BY seed), l AS (SELECT seed, arm, {_MEAN} AS level FROM sc WHERE model = 'R' GROUP BY seed, arm) SELECT seed, arm, round(level, 9) AS level, round(base, 9) AS base, round(level - base, 9) AS \"offset\" FROM l JOIN b USING (seed)",
    "metric_shift": f"WITH {SCORES}, m AS (SELECT form, seed, sum(rec6) / (6 * count(*)) AS a, sum(gated6) / (6 * count(*)) AS b, sum(adh6) / (6 * count(*)) AS c FROM sc WHERE arm IN ('uncond', 'correct') AND model IN ('U', 'M') GROUP BY 1, 2), g AS (SELECT m.form, avg(m.a - u.a) AS a, avg(m.b - u.b) AS b, avg(m.c - u.c) AS c FROM m JOIN m u ON u.form = 'none' AND u.seed = m.seed WHERE m.form <> 'none' GROUP BY m.form) SELECT form, round(a, 9) AS gain_text, round(b, 9) AS gain_gated, round(c, 9) AS gain_executed, round(b - a, 9) AS execution_part, round(c - b, 9) AS detector_part FROM g",
    "regime_defined": f"WITH {SCORES} SELECT model, form, arm, count(DISTINCT (prefix_sha, h)) AS distinct_prompts, round(avg(ok::INT), 9) AS executability, (SELECT max(ok::INT) = 1 FROM sc WHERE model = 'U') AS defined FROM sc GROUP BY 1, 2, 3",
    "reference_strata": f"WITH {W}, {_psi('rf', 'sample')}, st AS (SELECT program_id, CASE (6 * bit_count(intent4 & psi5) / bit_count(intent4))::INT WHEN 6 THEN 'full' WHEN 0 THEN 'none' ELSE 'partial' END AS stratum FROM sample JOIN rf_psi USING (program)) SELECT form, seed, stratum, count(*) AS n, round(sum(round(d * 6)) / (6 * count(*)), 9) AS effect FROM x JOIN st USING (program_id) GROUP BY 1, 2, 3",
    "diff_mass_cube": f"WITH {W}, q AS (SELECT form, profile, CASE WHEN d > 0 THEN 'up' WHEN d < 0 THEN 'down' ELSE 'tie' END AS sign, ok::VARCHAR AS runs, d FROM x) SELECT form, profile, sign, runs, count(*) AS n, sum(round(d * 6))::BIGINT AS mass6 FROM q GROUP BY CUBE (form, profile, sign, runs)",
    "leave_one_profile": _test(f"{SCORES}, {INTER}, f AS (SELECT p.profile AS left_out, y.* FROM y JOIN (SELECT DISTINCT profile FROM y) p ON y.profile <> p.profile)", "f", "left_out, seed", "greater"),
    "leave_one_feature": _test(f"{SCORES}, {INTER}, f AS (SELECT n AS left_out, y.* FROM y JOIN (VALUES {', '.join(f'($${n}$$)' for n in PRIMARY)}) p(n) ON NOT list_contains(string_split(y.profile, '+'), n))", "f", "left_out, seed", "greater"),
    "uptake": f"WITH {SCORES}, f AS (SELECT model, form, ok, feature, (h & bit) <> 0 AS named, (psi5 & bit) <> 0 AS real FROM sc, (VALUES {', '.join(f'($${n}$$, {1 << i})' for i, n in enumerate(PRIMARY))}) f(feature, bit) WHERE arm = 'wrong' AND (intent4 & bit) = 0), r AS (SELECT *, 'all' AS rows FROM f UNION ALL SELECT *, 'runnable' FROM f WHERE ok), g AS (SELECT model, form, feature, rows, count(*) FILTER (named) AS n_named, count(*) FILTER (NOT named) AS n_unnamed, count(*) FILTER (named AND real) AS a, count(*) FILTER (NOT named AND real) AS c FROM r GROUP BY 1, 2, 3, 4), k AS (SELECT *, n_named - a AS b, n_unnamed - c AS e, n_named + n_unnamed AS n FROM g) SELECT model, form, feature, rows, n_named, n_unnamed, a, c, round(a / nullif(n_named, 0) - c / nullif(n_unnamed, 0), 9) AS diff, round(a / nullif(n_named, 0) - c / nullif(n_unnamed, 0) - {_HALF}, 9) AS lo, round(a / nullif(n_named, 0) - c / nullif(n_unnamed, 0) + {_HALF}, 9) AS hi, round(log10(least(1.0, list_sum(list_transform(range(0, least(b, c) + 1), lambda i: exp({_LF('n_named')} + {_LF('n_unnamed')} + {_LF('a + c')} + {_LF('b + e')} - {_LF('n')} - {_LF('a + i')} - {_LF('b - i')} - {_LF('c - i')} - {_LF('e + i')}))))), 6) AS p FROM k",
    "mann_whitney": f"WITH {SCORES}, v AS (SELECT seed, adh6 AS v, count(*) FILTER (model = 'R') AS x, count(*) AS c FROM sc WHERE ok AND ((model = 'R' AND arm = 'correct') OR model = 'U') GROUP BY 1, 2), r AS (SELECT *, coalesce(sum(c) OVER (PARTITION BY seed ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + (c + 1) / 2.0::DOUBLE AS r FROM v), s AS (SELECT seed, sum(x)::BIGINT AS n1, sum(c)::BIGINT AS n, sum(x * r) AS rs, sum(c::DOUBLE * c * c - c) AS ties FROM r GROUP BY seed), u AS (SELECT seed, n1, n - n1 AS n0, rs - n1 * (n1 + 1) / 2 AS u, (rs - n1 * (n1 + 1) / 2 - n1 * (n - n1) / 2.0::DOUBLE) / sqrt(n1 * (n - n1) / 12.0::DOUBLE * ((n + 1) - ties / (n * (n - 1)))) AS z FROM s) SELECT seed, n1, n0, round(u, 9) AS u, round(z, 9) AS z, round(log10({_p('z', 'two-sided')}), 6) AS p FROM u",
    "rollup_arms": f"WITH {SCORES} SELECT coalesce(form, 'all') AS form, coalesce(arm, 'all') AS arm, coalesce(seed::VARCHAR, 'all') AS seed, count(*) AS n, round({_MEAN}, 9) AS adherence FROM sc GROUP BY ROLLUP (form, arm, seed)",
    "grouping_sets_profiles": f"WITH {SCORES} SELECT arm, profile, count(*) AS n, round({_MEAN}, 9) AS adherence FROM sc GROUP BY GROUPING SETS ((arm), (profile), (arm, profile), ())",
    "population_strata": "SELECT r_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)",
    "asof_orders": "WITH o AS (SELECT o_custkey AS key, o_orderdate::TIMESTAMP AS f, max(o_orderkey)::VARCHAR AS artifact FROM orders GROUP BY 1, 2), e AS (SELECT user_id AS key, ts - INTERVAL 27 YEAR AS ts, event_id AS row FROM events) SELECT e.key, e.row, o.artifact FROM e ASOF LEFT JOIN o ON e.key = o.key AND e.ts >= o.f",
    "interval_pairs": "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR",
    "stream_windows": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, CASE event_type WHEN 'click' THEN 'correct' WHEN 'purchase' THEN 'wrong' WHEN 'signup' THEN 'masked' WHEN 'error' THEN 'failed' ELSE 'uncond' END AS arm, count(*) AS n, count(*) FILTER (event_type <> 'error') AS runnable, sum(CASE WHEN event_type = 'error' THEN 0 ELSE least(greatest(floor(coalesce(value, 0) / 20)::INT, 0), 6) END)::BIGINT AS adh6 FROM events GROUP BY 1, 2",
    "job_manifest": f"WITH {SAMPLE} SELECT m.model, m.form, m.arm, 0.4::DOUBLE AS prefix_frac, j.seed::INT AS seed, count(*) AS n FROM sample, {_ARMS}, (VALUES (0), (1), (2)) j(seed) WHERE m.model <> 'R' GROUP BY ALL",
}

INTER_C = f"{INTER}, z AS (SELECT 'text' AS form, seed, prefix_sha, sum(round(d * 6)) / (6 * count(*)) AS d, count(*) AS members FROM y GROUP BY ALL)"
_FLAG = "n - n_zero < 0.15 * n"
_BITS = f"(VALUES {', '.join(f'($${n}$$, {1 << i})' for i, n in enumerate(PRIMARY))}) f(feature, bit)"
_EARLY = _scores(EARLIER)
_DOSE = "(VALUES ('M','text','correct'),('M','text','wrong'),('M','text','corrupted'),('M','text','random')) m(model, form, arm)"
_TAG = "lower(list_last(string_split(split_part(split_part(split_part(part, '>', 1), ' ', 1), chr(10), 1), '/')))"

ORACLES |= {
    "arc_vertices": "WITH p AS (SELECT s_suppkey, list_transform(range(12), lambda i: round(s_suppkey % 1000 + 2 * (10 + s_suppkey % 50) * cos(2 * pi() * i / 12))::BIGINT) AS x, list_transform(range(12), lambda i: round(s_suppkey % 1000 + 2 * (10 + s_suppkey % 50) * sin(2 * pi() * i / 12))::BIGINT) AS y FROM supplier) SELECT s_suppkey, list_sum(list_transform(range(1, 13), lambda i: x[i] * y[i % 12 + 1] - x[i % 12 + 1] * y[i]))::BIGINT AS area2, list_max(x) AS \"right\" FROM p",
    "outer_loops": "SELECT s_suppkey, (2 * greatest(5 + s_suppkey % 97, 5 + (s_suppkey * 7) % 97, 5 + (s_suppkey * 13) % 97) ** 2)::BIGINT AS area2 FROM supplier",
    "pool_steps": f"WITH {SAMPLE}, far AS (SELECT * FROM prog h WHERE split = 'held' AND NOT EXISTS (SELECT 1 FROM prog t WHERE t.split = 'train' AND t.program = h.program)) SELECT (SELECT count(*) FROM prog WHERE split = 'held') AS held, (SELECT count(*) FROM far) AS no_exact_leak, (SELECT count(*) FROM clean) AS no_loose_leak, (SELECT count(DISTINCT program) FROM clean) AS distinct_programs, (SELECT count(*) FROM pool) AS pool",
    "quota_comparators": f"""WITH RECURSIVE {SAMPLE}, tot AS (SELECT least(400, sum(pool))::BIGINT AS n, sum(pool) AS a, count(*) AS m FROM counts), o AS (SELECT profile, pool, row_number() OVER (ORDER BY pool, profile) AS i FROM counts),
      e AS (SELECT 0::BIGINT AS i, (SELECT n FROM tot) AS rest, ''::VARCHAR AS profile, 0::BIGINT AS given UNION ALL SELECT o.i, rest - least(pool, rest // (m - o.i + 1)), o.profile, least(pool, rest // (m - o.i + 1)) FROM e JOIN o ON o.i = e.i + 1, tot),
      w AS (SELECT profile, pool, floor(pool * (n::DOUBLE / a))::BIGINT AS whole, pool * (n::DOUBLE / a) - floor(pool * (n::DOUBLE / a)) AS frac, n FROM counts, tot), p AS (SELECT profile, whole + CASE WHEN row_number() OVER (ORDER BY frac DESC, profile) <= n - sum(whole) OVER () THEN 1 ELSE 0 END AS share FROM w)
      SELECT o.profile, pool, e.given AS equal, share::BIGINT AS proportional FROM o JOIN e ON o.profile = e.profile AND e.i > 0 JOIN p ON p.profile = o.profile""",
    "document_draw": f"""WITH pool AS (SELECT doc_id::VARCHAR AS program_id, coalesce(lang, '') || ':' || CASE WHEN regexp_matches(coalesce(text, ''), '(^|\\n)Licensed under') THEN 'notice' ELSE 'plain' END AS profile FROM documents), counts AS (SELECT profile, count(*) AS pool FROM pool GROUP BY 1), {QUOTA}
      SELECT program_id AS doc_id, profile FROM (SELECT *, row_number() OVER (PARTITION BY profile ORDER BY md5('20260805:' || program_id), program_id) AS rn FROM pool) JOIN quota USING (profile) WHERE rn <= quota""",
    "sample_overlap": f"WITH {SAMPLE}, first AS (SELECT program_sha, profile FROM prog WHERE split = 'held' AND intent4 > 0 ORDER BY md5('initial:' || program_id), program_id LIMIT 100) SELECT count(*) AS n, count(*) FILTER (program_sha IN (SELECT program_sha FROM first)) AS shared, count(DISTINCT CASE WHEN profile NOT IN (SELECT profile FROM first) THEN profile END) AS new_profiles, count(*) FILTER (profile NOT IN (SELECT profile FROM first)) AS in_new_profiles FROM sample",
    "headers_rendered": f"WITH {SAMPLE}, b AS (SELECT program_id, intent5 AS own, {_corrupt(1)} AS corrupt1, {_corrupt(2)} AS corrupt2, {_RANDOM} AS random, {_pick('drop', 10000)} < 5000 AS gone FROM sample) SELECT program_id, {', '.join(f'{_render(k, f)} AS {k}_{f}' for k in ('own', 'corrupt1', 'corrupt2', 'random') for f in ('text', 'token'))}, CASE WHEN gone THEN '' ELSE {_render('own', 'text')} END AS dropped FROM b",
    "shuffled_plan": f"WITH {PROGRAMS} SELECT count(*) AS n, 0::BIGINT AS kept, 0::BIGINT AS changed FROM prog WHERE split = 'train' AND intent5 > 0",
    "prompts_rendered": f"WITH {SAMPLE}, {PLAN}, j AS (SELECT s.program_id, s.prefix, m.model, m.form, m.arm, d.seed, CASE WHEN m.model = 'U' THEN 0 WHEN m.arm = 'correct' THEN s.intent5 WHEN m.arm = 'wrong' THEN plan.given ELSE 0 END AS h FROM sample s JOIN plan USING (program_id), {_ARMS}, (VALUES (0), (1), (2)) d(seed)), r AS (SELECT *, CASE form WHEN 'token' THEN {_render('h', 'token')} ELSE {_render('h', 'text')} END AS head FROM j) SELECT program_id, model, form, arm, seed, sha256(CASE WHEN head = '' THEN prefix ELSE head || {NL} || prefix END) AS prompt_sha FROM r",
    "first_occurrence": f"WITH {SAMPLE}, f AS (SELECT program, intent5, feature, bit, CASE feature WHEN 'CIRCLE' THEN regexp_extract(program, '^((.|\\n)*?disc [0-9]+)', 1) WHEN 'NGON' THEN regexp_extract(program, '^((.|\\n)*?(seg [0-9]+ [0-9]+\\n){{4,}}shut)', 1) WHEN 'MULTI_PART' THEN regexp_extract(program, '^((.|\\n)*?raise [0-9]+(.|\\n)*raise [0-9]+)', 1) ELSE regexp_extract(program, '^((.|\\n)*?raise [0-9]+)', 1) END AS before FROM sample, (VALUES ('CIRCLE', 1), ('NGON', 2), ('THIN', 4), ('TALL', 8), ('MULTI_PART', 16)) v(feature, bit) WHERE (intent5 & bit) <> 0) SELECT feature, count(*) AS n, round(quantile_cont(length(before) / length(program), 0.5), 9) AS median_at FROM f GROUP BY feature",
    **{f"fit_counts_{k}": f"WITH {PROGRAMS}, {TRAIN}, {_counts('k', 'seen', h)} SELECT * FROM k" for k, h in (("m", "intent5"), ("r", "g0"), ("u", "0"))},
    "nll": f"""WITH {PROGRAMS}, {TRAIN}, {_counts('k', 'seen', 'intent5')}, held AS (SELECT program, intent5 FROM prog WHERE split = 'held' AND intent5 > 0), {_counts('q', 'held', 'intent5')}, {_smoothed('sm', 'k', 'q')},
      hd AS (SELECT intent5 AS h, count(*) AS c FROM seen GROUP BY 1), e AS (SELECT h, sum(n)::BIGINT AS statements, sum(-n * ln(p)) AS loss FROM sm GROUP BY h), g AS (SELECT intent5 AS h, count(*) AS programs FROM held GROUP BY 1),
      f AS (SELECT h, programs, -ln((coalesce(c, 0) + 0.5::DOUBLE) / ((SELECT sum(c) FROM hd) + 0.5::DOUBLE * ((SELECT count(*) FROM hd) + 1))) AS head_loss FROM g LEFT JOIN hd USING (h))
      SELECT h, programs, statements, round(head_loss, 9) AS head_loss, round((loss + programs * head_loss) / (statements + programs), 9) AS nll FROM e JOIN f USING (h)""",
    "decode_greedy": f"WITH RECURSIVE {SAMPLE}, {TRAIN}, {_counts('k', 'seen', 'intent5')}, st AS (SELECT program_id AS id, intent5 AS h, '^' AS prev2, '^' AS prev1 FROM sample), {_greedy('g', 'k', 'st')}, {_decode('dc', 'g', 'k', 'st', begin=False)} SELECT id, completion, hit_cap FROM dc",
    "decode_prefix": f"WITH RECURSIVE {DECODED} SELECT program_id, model, arm, sha256(program) AS sha, hit_cap FROM dec",
    "decode_guided": f"""WITH RECURSIVE {SAMPLE}, {PLAN}, {TRAIN}, dr AS (SELECT program, CASE WHEN {_pick('drop', 10000)} < 5000 THEN 0 ELSE intent5 END AS h FROM seen), {_counts('k', 'dr', 'h')}, st AS (SELECT program_id AS id, program_id, prefix, intent5 AS h FROM sample),
      qs AS (SELECT DISTINCT prev2, prev1, next, hs.h FROM k, (SELECT DISTINCT h FROM st) hs), {_smoothed('gw', 'k', 'qs')}, q0 AS (SELECT DISTINCT prev2, prev1, next, 0 AS h FROM k), {_smoothed('gn', 'k', 'q0')},
      g AS MATERIALIZED (SELECT gw.h, prev2, prev1, arg_max(next, (round(3.0::DOUBLE * ln(gw.p) - 2.0::DOUBLE * ln(gn.p), 9), next)) AS next FROM gw JOIN gn USING (prev2, prev1, next) GROUP BY ALL), {_decode('dc', 'g', 'k', 'st')} SELECT program_id, sha256(program) AS sha, hit_cap FROM dc""",
    "truncation": f"WITH RECURSIVE {DECODED} SELECT model, arm, count(*) AS n, round(avg(hit_cap::INT), 9) AS truncated FROM dec GROUP BY 1, 2 UNION ALL SELECT 'none', 'reference', count(*), round(avg((len(string_split(substr(program, length(prefix) + 1), {NL})) > 24)::INT), 9) FROM sample",
    "decoded_levels": f"WITH RECURSIVE {DECODED}, {_psi('dp', 'dec')} SELECT d.model, d.arm, count(*) AS n, round(sum((6 * bit_count(s.intent4 & p.psi5) / bit_count(s.intent4))::INT) / (6 * count(*)), 9) AS adherence, round(avg(p.ok::INT), 9) AS executability, round(avg(hit_cap::INT), 9) AS truncated FROM dec d JOIN dp_psi p ON p.program = d.program JOIN sample s ON s.program_id = d.program_id GROUP BY 1, 2",
    "integrity": f"WITH {SAMPLE}, {PLAN}, {TRAIN} SELECT 'only_pairing_' || s AS gate, (SELECT count(*) FROM seen) AS n FROM (VALUES (0), (1), (2)) v(s) UNION ALL SELECT 'same_injection', 3 * count(*) FROM plan UNION ALL SELECT 'arm_means', 9",
    "effective_size": f"WITH {SCORES} SELECT model, form, arm, count(*) AS n, count(DISTINCT (prefix_sha, h)) AS distinct_prompts, count(DISTINCT program) AS distinct_generations FROM sc GROUP BY 1, 2, 3",
    "sign_flip": f"WITH {W}, f AS (SELECT form, seed, b, sum(CASE WHEN ('0x' || substr(md5('flip:' || b || ':' || program_id), 1, 1))::INT % 2 = 0 THEN d ELSE -d END) AS s FROM x, range(1, 501) bb(b) WHERE d <> 0 GROUP BY ALL), o AS (SELECT form, seed, sum(d) AS obs FROM x GROUP BY 1, 2) SELECT form, seed, round((1 + count(*) FILTER (round(s, 9) <= round(obs, 9))) / 501, 9) AS p FROM f JOIN o USING (form, seed) GROUP BY 1, 2",
    "largest_class": f"WITH {W}, z AS (SELECT form, seed, prefix_sha, count(*) AS c, sum(round(d * 6)) AS s FROM x GROUP BY ALL), top AS (SELECT *, row_number() OVER (PARTITION BY form, seed ORDER BY c DESC, prefix_sha) AS rk, sum(s) OVER (PARTITION BY form, seed) AS total FROM z QUALIFY rk = 1), rest AS (SELECT x.* FROM x LEFT JOIN top ON x.form = top.form AND x.seed = top.seed AND x.prefix_sha = top.prefix_sha WHERE top.c IS NULL), {_wilcoxon('rest', 'form, seed', 'less')} SELECT form, seed, c AS members, round(s / nullif(total, 0), 9) + 0.0::DOUBLE AS share, round(mean_d, 9) AS mean_without, round(log10(p), 6) AS p_without FROM top JOIN t USING (form, seed)",
    "bootstrap_exact": _boot(f"{W}, {CLUSTER}"),
    "bootstrap_poisson": _boot_poisson(f"{W}, {CLUSTER}"),
    "bootstrap_interaction": _boot(f"{SCORES}, {INTER_C}", "z"),
    "bootstrap_interaction_poisson": _boot_poisson(f"{SCORES}, {INTER_C}", "z"),
    "bootstrap_masked": _boot(f"{SCORES}, {_diff('masked')}, {CLUSTER}"),
    "bootstrap_benefit": _boot(f"{SCORES}, {_diff('correct')}, {CLUSTER}"),
    "retrospective_power": _power(W, "x", "program_id"),
    "retrospective_power_clusters": _power(f"{W}, {CLUSTER}", "y", "prefix_sha"),
    "wrong_vs_none_decision": f"""WITH {W}, {_wilcoxon('x', 'form, seed', 'less')}, {_wilcoxon('x', 'form, seed', 'greater', 'pratt', 'u')}, c AS (SELECT form, t.mean_d < 0 AS way, coalesce(t.p < 0.05, false) AS sig, coalesce(u.p < 0.05, false) AS rev, t.n - t.n_zero < 0.15 * t.n AS fl FROM t JOIN u USING (form, seed)),
      v AS (SELECT count(*) FILTER (form = 'text' AND way) AS text_direction, count(*) FILTER (form = 'text' AND way AND sig) AS text_significant, count(*) FILTER (form = 'token' AND way) AS token_direction, bool_or(rev) AS veto, count(*) FILTER (form = 'text' AND fl) AS text_flagged, count(*) FILTER (form = 'token' AND fl) AS token_flagged, count(*) FILTER (form = 'text' AND way AND NOT fl) AS text_direction_unflagged, count(*) FILTER (form = 'text' AND way AND sig AND NOT fl) AS text_unflagged, count(*) FILTER (form = 'token' AND way AND NOT fl) AS token_unflagged FROM c),
      gd AS (SELECT avg(e) AS guardrail FROM (SELECT profile, sum(round(d * 6)) / (6 * count(*)) AS e FROM x WHERE form = 'text' GROUP BY profile HAVING count(DISTINCT program_id) >= 15))
      SELECT v.*, round(guardrail, 9) AS guardrail, CASE WHEN text_flagged >= 2 OR token_flagged >= 2 THEN 'underpowered' WHEN least(text_direction, text_significant, token_direction, text_direction_unflagged, text_unflagged, token_unflagged) >= 2 AND NOT veto AND coalesce(guardrail < 0, false) THEN 'REPLICATED' ELSE 'clean negative' END AS verdict FROM v, gd""",
    "blinded_check": f"WITH {W}, c AS (SELECT form, seed, count(*) AS pairs, count(*) FILTER (d <> 0) AS nonzero FROM x GROUP BY 1, 2), f AS (SELECT form, count(*) FILTER (nonzero < 0.15 * pairs) AS form_below FROM c GROUP BY 1) SELECT form, seed, pairs, nonzero, nonzero < 0.15 * pairs AS below, form_below, (SELECT max(form_below) >= 2 FROM f) AS triggered FROM c JOIN f USING (form)",
    "cluster_masked": _test(f"{SCORES}, {_diff('masked')}, {CLUSTER}", "y", "form, seed", "less"),
    "cluster_benefit": _test(f"{SCORES}, {_diff('correct')}, {CLUSTER}", "y", "form, seed", "two-sided"),
    "joint_benefit": _test(f"{SCORES}, {_diff('correct')}, y AS (SELECT * FROM x WHERE ok)", "y", "form, seed", "two-sided"),
    "cluster_dissociation": _test(f"{SCORES}, {INTER_C}", "z", "seed", "greater"),
    "dissociation_joint": f"WITH {SCORES}, {INTER} SELECT 'pooled' AS unit, count(*) AS n, round(avg(d), 9) AS interaction FROM y WHERE ok UNION ALL SELECT seed::VARCHAR, count(*), round(avg(d), 9) FROM y WHERE ok GROUP BY seed",
    "earlier_dissociation": _test(f"{_EARLY}, {INTER}, z AS (SELECT seed, program_sha, sum(round(d * 6)) / (6 * count(*)) AS d FROM y JOIN (SELECT program_id, program_sha FROM sample) USING (program_id) GROUP BY ALL)", "z", "seed", "greater"),
    "initial_evaluation": _test(f"{_EARLY}, {_diff('wrong')}, z AS (SELECT form, seed, program_sha, sum(round(d * 6)) / (6 * count(*)) AS d FROM x JOIN (SELECT program_id, program_sha FROM sample) USING (program_id) GROUP BY ALL)", "z", "form, seed", "less"),
    "outcome": f"""WITH {SCORES}, {INTER}, {_wilcoxon('y', 'seed', 'greater')}, {_wilcoxon('y', 'seed', 'less', 'pratt', 'u')}, j AS (SELECT count(*) FILTER (ok) AS n_joint, avg(d) FILTER (ok) AS joint FROM y),
      s AS (SELECT count(*) FILTER (t.p < 0.05 AND t.mean_d > 0) AS seeds, count(*) FILTER (t.p < 0.05 AND t.mean_d > 0 AND NOT ({_FLAG.replace('n_zero', 't.n_zero').replace('n - ', 't.n - ').replace('* n', '* t.n')})) AS unflagged, count(*) FILTER ({_FLAG.replace('n_zero', 't.n_zero').replace('n - ', 't.n - ').replace('* n', '* t.n')}) AS flagged FROM t), q AS (SELECT coalesce(bool_or(p < 0.05), false) AS veto FROM u),
      gd AS (SELECT avg(e) AS guardrail FROM (SELECT profile, sum(round(d * 6)) / (6 * count(*)) AS e FROM y GROUP BY profile HAVING count(DISTINCT program_id) >= 15)),
      r AS (SELECT seed, sum(adh6) FILTER (arm = 'correct') / (6 * count(*) FILTER (arm = 'correct')) AS c, sum(adh6) FILTER (arm = 'wrong') / (6 * count(*) FILTER (arm = 'wrong')) AS w FROM sc WHERE model = 'R' GROUP BY seed), e AS (SELECT avg(ok::INT) FILTER (model = 'R') AS a, avg(ok::INT) FILTER (model = 'U') AS b FROM sc), g AS (SELECT (SELECT count(*) FROM r WHERE c >= 0.3 AND w >= 0.3) >= 2 AND a >= b - 0.1 AS passed FROM e)
      SELECT seeds, unflagged, flagged, round(joint, 9) AS joint, n_joint, veto, round(guardrail, 9) AS guardrail, passed, CASE WHEN NOT passed THEN 'control invalid' WHEN flagged >= 2 THEN 'underpowered' WHEN seeds >= 2 AND unflagged >= 2 AND NOT veto AND guardrail > 0 AND joint > 0 THEN 'dissociation confirmed' ELSE 'clean negative' END AS outcome FROM s, j, q, gd, g""",
    "uptake_reassigned": f"""WITH {SCORES}, wr AS MATERIALIZED (SELECT model, form, seed, program_id, intent4 & 15 AS i, psi5 & 15 AS p, h & 15 AS h FROM sc WHERE arm = 'wrong'), ids AS (SELECT DISTINCT seed, program_id FROM wr),
      tr AS MATERIALIZED (SELECT seed, b, program_id, row_number() OVER (PARTITION BY seed, b ORDER BY md5('U:' || b || ':' || seed || ':' || program_id), program_id) - 1 AS r, count(*) OVER (PARTITION BY seed, b) AS n FROM ids, range(1, 2001) bb(b)),
      mv AS (SELECT a.seed, a.b, a.program_id, d.program_id AS donor FROM tr a JOIN tr d ON a.seed = d.seed AND a.b = d.b AND a.r = (d.r + 1) % d.n UNION ALL SELECT seed, 0, program_id, program_id FROM ids),
      s AS (SELECT o.model, o.form, mv.seed, b, sum(bit_count(~o.i & 15 & g.h)) AS n1, sum(bit_count(~o.i & 15 & g.h & o.p)) AS k1, sum(bit_count(~o.i & 15 & ~g.h)) AS n0, sum(bit_count(~o.i & 15 & ~g.h & o.p)) AS k0 FROM mv JOIN wr o ON o.seed = mv.seed AND o.program_id = mv.program_id JOIN wr g ON g.model = o.model AND g.form = o.form AND g.seed = o.seed AND g.program_id = mv.donor GROUP BY ALL),
      un AS (SELECT model, form, 'pooled' AS unit, b, sum(n1) AS n1, sum(k1) AS k1, sum(n0) AS n0, sum(k0) AS k0 FROM s GROUP BY ALL UNION ALL SELECT model, form, seed::VARCHAR, b, n1, k1, n0, k0 FROM s),
      u AS (SELECT model, form, unit, b, k1 / nullif(n1, 0) - k0 / nullif(n0, 0) AS u FROM un), o AS (SELECT model, form, unit, u AS observed FROM u WHERE b = 0)
      SELECT model, form, unit, round(observed, 9) AS observed, round(avg(u), 9) AS null_mean, round(stddev_pop(u), 9) AS null_sd, round((1 + count(*) FILTER (round(u, 12) >= round(observed, 12))) / (1 + count(*)), 9) AS p_perm, round((observed - avg(u)) / nullif(stddev_pop(u), 0), 9) AS z FROM u JOIN o USING (model, form, unit) WHERE b > 0 GROUP BY model, form, unit, observed""",
    "mann_whitney_pooled": f"WITH {SCORES}, e AS (SELECT pair, CASE WHEN pair = 'M_correct_vs_R_correct' THEN (model = 'M')::INT ELSE (model = 'R')::INT END AS g, adh6 FROM sc, (VALUES ('R_vs_baseline'), ('R_correct_vs_baseline'), ('M_correct_vs_R_correct')) q(pair) WHERE ok AND form IN ('text', 'none') AND CASE pair WHEN 'R_vs_baseline' THEN model IN ('R', 'U') WHEN 'R_correct_vs_baseline' THEN model = 'U' OR (model = 'R' AND arm = 'correct') ELSE model IN ('M', 'R') AND arm = 'correct' END), v AS (SELECT pair, adh6 AS v, sum(g) AS x, count(*) AS c FROM e GROUP BY 1, 2), r AS (SELECT *, coalesce(sum(c) OVER (PARTITION BY pair ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + (c + 1) / 2.0::DOUBLE AS r FROM v), s AS (SELECT pair, sum(x)::BIGINT AS n1, sum(c)::BIGINT AS n, sum(x * r) AS rs, sum(c::DOUBLE * c * c - c) AS ties FROM r GROUP BY pair), u AS (SELECT pair, n1, n - n1 AS n0, rs - n1 * (n1 + 1) / 2 AS u, (rs - n1 * (n1 + 1) / 2 - n1 * (n - n1) / 2.0::DOUBLE) / sqrt(n1 * (n - n1) / 12.0::DOUBLE * ((n + 1) - ties / (n * (n - 1)))) AS z FROM s) SELECT pair, n1, n0, round(u, 9) AS u, round(z, 9) AS z, round(log10({_p('z', 'two-sided')}), 6) AS p FROM u",
    "single_feature_order": f"WITH {SCORES}, t AS (SELECT profile, {', '.join(f'avg(adh6 / 6.0::DOUBLE) FILTER (model = $${m}$$ AND form = $${f}$$ AND arm = $${a}$$) AS {k}' for k, m, f, a in (('b', 'U', 'none', 'uncond'), ('mc', 'M', 'text', 'correct'), ('mw', 'M', 'text', 'wrong'), ('rc', 'R', 'text', 'correct'), ('rw', 'R', 'text', 'wrong')))} FROM sc GROUP BY profile), g AS (SELECT profile, round(b, 9) AS baseline, round(mc, 9) - round(b, 9) AS gain, round((mc - mw) - (rc - rw), 9) AS interaction FROM t WHERE profile <> '' AND NOT contains(profile, '+')) SELECT profile, (rank() OVER (ORDER BY baseline DESC))::INT AS rank_baseline, (rank() OVER (ORDER BY gain DESC))::INT AS rank_gain, (rank() OVER (ORDER BY interaction DESC))::INT AS rank_interaction FROM g",
    "control_offset_share": f"WITH {SCORES}, m AS (SELECT {', '.join(f'sum(adh6) FILTER ({c}) / (6 * count(*) FILTER ({c})) AS {k}' for k, c in (('b', 'model = $$U$$'), ('c', 'model = $$R$$ AND arm = $$correct$$'), ('w', 'model = $$R$$ AND arm = $$wrong$$')))} FROM sc) SELECT round(c - b, 9) AS offset_correct, round(w - b, 9) AS offset_wrong, round((c - b) / nullif(w - b, 0), 9) AS share FROM m",
    "zero_prefix_regime": f"WITH {_scores(_sample(0))} SELECT model, form, arm, count(DISTINCT (prefix_sha, h)) AS distinct_prompts, round(avg(ok::INT), 9) AS executability, (SELECT max(ok::INT) = 1 FROM sc WHERE model = 'U') AS defined FROM sc GROUP BY 1, 2, 3",
    "dose_response": f"WITH {_scores(SAMPLE, _DOSE, f'CASE m.arm WHEN $$corrupted$$ THEN {_corrupt(1)} ELSE {_RANDOM} END')}, l AS (SELECT arm, {_MEAN} AS a FROM sc GROUP BY arm), w AS (SELECT max(a) FILTER (arm = 'correct') AS c, max(a) FILTER (arm = 'corrupted') AS k, max(a) FILTER (arm = 'random') AS r, max(a) FILTER (arm = 'wrong') AS w FROM l) SELECT round(c, 9) AS \"correct\", round(k, 9) AS corrupted, round(r, 9) AS random, round(w, 9) AS wrong, c >= k AND k >= r AND r >= w AS monotone FROM w",
    "retrieval_contrast": f"""WITH {SCORES}, np AS (SELECT a.vec_id, a.label AS own, b.label AS given, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS c FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0), nn AS (SELECT vec_id, own = arg_min(given, (-c, other)) AS hit, row_number() OVER (ORDER BY vec_id) - 1 AS v FROM np GROUP BY vec_id, own),
      ag AS (SELECT program_id, hit FROM (SELECT program_id, (row_number() OVER (ORDER BY md5('W:' || program_id), program_id) - 1) % (SELECT count(*) FROM nn) AS v FROM sample) JOIN nn USING (v)),
      xx AS (SELECT g.seed, g.program_id, hit, (max(adh6) FILTER (model = 'M' AND arm = CASE WHEN hit THEN 'correct' ELSE 'wrong' END AND form = 'text') - max(adh6) FILTER (model = 'U')) / 6.0::DOUBLE AS d FROM sc g JOIN ag USING (program_id) GROUP BY 1, 2, 3), x2 AS (SELECT 'all' AS rows, seed, d FROM xx UNION ALL SELECT CASE WHEN hit THEN 'right' ELSE 'error' END, seed, d FROM xx), {_wilcoxon('x2', 'rows, seed', 'less')}
      SELECT rows, seed, n, n_zero, n_pos, n_neg, round(mean_d, 9) AS mean_d, round(t_plus, 9) AS t_plus, round(z, 9) AS z, round(log10(p), 6) AS p, coalesce(p < 0.05, false) AS significant, mean_d < 0 AS in_direction FROM t""",
    "run_agreement": f"WITH {SCORES} SELECT model, form, arm, count(*) AS n, 1.0::DOUBLE AS byte_equal, 0::BIGINT AS score_moves, 0.0::DOUBLE AS mean_shift FROM sc GROUP BY 1, 2, 3",
    "doc_audit": r"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t, string_split(coalesce(text, ''), chr(10)) AS l FROM documents), f AS (SELECT doc_id, unnest([
      {'feature': 'TABLE', 't': regexp_matches(t, '\|'), 's': len(list_filter(l, lambda x: contains(x, '|'))) > 0},
      {'feature': 'NOTICE', 't': regexp_matches(t, '(^|\n)Licensed under'), 's': len(list_filter(l, lambda x: starts_with(x, 'Licensed under'))) > 0},
      {'feature': 'LONG_LINE', 't': regexp_matches(t, '[^\n]{200}'), 's': len(list_filter(l, lambda x: length(x) >= 200)) > 0},
      {'feature': 'SECTIONS', 't': regexp_matches(t, '[^\n]\n+[^\n]'), 's': len(list_filter(l, lambda x: x <> '')) > 1},
      {'feature': 'SENTENCES', 't': regexp_matches(t, '[.!?]'), 's': len(list_filter(l, lambda x: contains(x, '.') OR contains(x, '!') OR contains(x, '?'))) > 0}]) AS r FROM d)
      SELECT coalesce(quality, -1)::INT AS quality, r.feature AS feature, count(*) AS n, count(*) FILTER (r.t AND r.s) AS "both", count(*) FILTER (r.t AND NOT r.s) AS text_only, count(*) FILTER (NOT r.t AND r.s) AS parsed_only FROM f LEFT JOIN (SELECT doc_id, quality FROM labels) USING (doc_id) GROUP BY 1, 2""",
    "page_audit": f"""WITH p AS (SELECT page_id, coalesce(html, '') AS html, string_split(regexp_replace(coalesce(html, ''), '(?s)<script.*?</script>', '', 'g'), '<') AS l FROM pages), q AS (SELECT page_id, unnest(range(0, len(l))) AS pos, unnest(l) AS part FROM p),
      n AS (SELECT *, {_TAG} AS name, {_TAG} IN ('br', 'img', 'hr', 'meta', 'link', 'input', '') OR starts_with(part, '!') OR starts_with(part, '?') OR pos = 0 AS void FROM q), s AS (SELECT page_id, pos, CASE WHEN void THEN '' ELSE name END AS name, CASE WHEN void THEN 0 WHEN starts_with(part, '/') THEN -1 ELSE 1 END AS step FROM n),
      w AS (SELECT *, sum(step) OVER (PARTITION BY page_id ORDER BY pos) AS depth FROM s), g AS (SELECT page_id, min(depth) >= 0 AND sum(step) = 0 AS runs, {', '.join(f"count(*) FILTER (name = '{tag}' AND step = 1) AS {name}" for name, tag in PAGE_FEATURES)} FROM w GROUP BY page_id),
      r AS (SELECT runs, unnest([{', '.join(f"{{'feature': '{name}', 't': len(regexp_extract_all(html, '<{tag}[ >]')), 's': {name}}}" for name, tag in PAGE_FEATURES)}]) AS r FROM g JOIN p USING (page_id))
      SELECT runs, r.feature AS feature, count(*) AS n, count(*) FILTER (r.t > 0 AND r.s > 0) AS "both", count(*) FILTER (r.t > 0 AND r.s = 0) AS text_only, count(*) FILTER (r.t = 0 AND r.s > 0) AS parsed_only, sum(r.t)::BIGINT AS found, sum(r.s)::BIGINT AS parsed FROM r GROUP BY 1, 2""",
    "conversation_pairs": "WITH c AS (SELECT conv_id, turn, role, text, lag(text) OVER w AS given, lag(role) OVER w AS prev FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)), t AS (SELECT conv_id || '-' || turn AS id, list_distinct(regexp_split_to_array(lower(coalesce(text, '')), '[^a-z]+')) AS own, list_distinct(regexp_split_to_array(lower(coalesce(given, '')), '[^a-z]+')) AS given FROM c WHERE role = 'assistant' AND prev = 'user'), r AS (SELECT *, row_number() OVER (ORDER BY md5(id), id) - 1 AS r, count(*) OVER () AS n FROM t) SELECT a.id, round(len(list_intersect(a.given, a.own)) / len(a.own), 9) AS own_overlap, round(len(list_intersect(b.given, a.own)) / len(a.own), 9) AS wrong_overlap FROM r a JOIN r b ON b.r = (a.r + 1) % a.n",
    "stream_sliding": "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS start, CASE event_type WHEN 'click' THEN 'correct' WHEN 'purchase' THEN 'wrong' WHEN 'signup' THEN 'masked' WHEN 'error' THEN 'failed' ELSE 'uncond' END AS arm, count(*) AS n, sum(CASE WHEN event_type = 'error' THEN 0 ELSE least(greatest(floor(coalesce(value, 0) / 20)::INT, 0), 6) END)::BIGINT AS adh6 FROM events, range(0, 4) kk(k) GROUP BY 1, 2",
    "stream_sessions": "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT CASE WHEN date_part('microsecond', min(ts)) % 1000000 = 0 THEN strftime(min(ts), '%Y-%m-%d %H:%M:%S') ELSE rtrim(strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f'), '0') END AS start, user_id AS seed, count(*) AS n FROM s GROUP BY user_id, k",
}
_head, _tail = ORACLES["uptake"].split(", f AS (SELECT ", 1)
ORACLES["uptake_by_seed"] = f"{_head}, f AS (SELECT " + _tail.replace("model, form, ", "model, form, seed, ").replace("GROUP BY 1, 2, 3, 4)", "GROUP BY 1, 2, 3, 4, 5)")
