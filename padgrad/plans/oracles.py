"""SQL twins of the catalogue's queries, written from the definitions for DuckDB."""

from __future__ import annotations

import numpy as np

from padgrad.functions.fixedpoint import PRIMES

P60 = 2**60


def prf(*parts: str) -> str:
    return "('0x' || substr(sha256(concat_ws(':', " + ", ".join(parts) + ")), 1, 15))::BIGINT"


def uni(*parts: str) -> str:
    return f"(({prf(*parts)})::DOUBLE + 0.5) / {float(P60)!r}"


def wrap(v: str, k: int = 48) -> str:
    h, m = 2 ** (k - 1), 2**k
    return f"((((({v})::HUGEINT + {h}) % {m}) + {m}) % {m} - {h})::BIGINT"


def mod(v: str, m: str | int) -> str:
    return f"(((({v})::HUGEINT % {m}) + {m}) % {m})::BIGINT"


def quant(v: str, k: int = 48, f: int = 24) -> str:
    return f"floor(({v})::DOUBLE * {float(2**f)!r} + 0.5)::BIGINT"


def mul(a: str, b: str, k: int = 48, f: int = 24) -> str:
    return wrap(f"(({a})::HUGEINT * ({b})::HUGEINT) >> {f}", k)


def pad(seed: str, device: str, kind: str, i: str, j: str, k: int = 48) -> str:
    a, b = (f"least({i}, {j})", f"greatest({i}, {j})") if kind == "xi" else (i, j)
    return wrap(mod(prf(f"'{seed}'", device, f"'{kind}'", a, b), 2**k), k)


def examples(devices: int, bits: int = 12) -> str:
    """Common tables ``ex``, ``xs`` (a row for each feature) and ``ys`` (for each output)."""
    return f"""ex AS (
  SELECT CAST(ntile({devices}) OVER (ORDER BY label, vec_id) - 1 AS INT) AS device, vec_id, label, embedding FROM embeddings
), dims AS (SELECT range::INT AS i FROM range(64)), outs AS (SELECT range::INT AS j FROM range(10)),
xs AS (SELECT device, vec_id, label, i, floor(embedding[i + 1]::DOUBLE * {2**bits})::BIGINT AS a FROM ex, dims),
ys AS (SELECT vec_id, j, CASE WHEN label = j THEN {2**bits} ELSE 0 END AS b FROM ex, outs),
gram AS (SELECT l.device, l.i, r.i AS j, sum(l.a * r.a)::BIGINT AS v FROM xs l JOIN xs r USING (vec_id) GROUP BY ALL),
crs AS (SELECT x.device, x.i, y.j, sum(x.a * y.b)::BIGINT AS v FROM xs x JOIN ys y USING (vec_id) GROUP BY ALL)"""


def eps_sql(dims: int) -> str:
    return f"eps AS (SELECT k.range::INT AS k, j.range::INT AS j, ((k.range * 7 + j.range * 3) % 11 - 5)::BIGINT AS e FROM range({dims}) k, range(10) j)"


def code_values(codes: list[np.ndarray]) -> str:
    rows = [f"({i},{j},{lane},{int(b[i, j])})" for lane, b in enumerate(codes) for i, j in zip(*np.nonzero(b), strict=True)]
    return f"code(device, peer, lane, b) AS (VALUES {', '.join(rows)})"


PRIME_OF = "CASE lane " + " ".join(f"WHEN {k} THEN {p}" for k, p in enumerate(PRIMES)) + " END"


def fleet() -> str:
    return """fleet AS (
  SELECT n_nationkey::INT AS device, greatest(n_regionkey - 1, 0)::INT AS class,
         CASE greatest(n_regionkey - 1, 0) WHEN 0 THEN 25e6 WHEN 1 THEN 5e6 WHEN 2 THEN 2.5e6 ELSE 1.25e6 END::DOUBLE AS tau
  FROM nation)"""


def latency(epochs: int, rho: float, bits: float, seed: str) -> str:
    wire = bits * 1.1

    def sends(kind):
        return f"greatest(1.0, ceil(ln({uni(repr(seed), 'epoch', 'device', repr(kind))}) / ln(0.1)))"

    return f"""{fleet()}, lat AS (
  SELECT epoch, device, class, {rho!r} / tau AS comp_s, -ln({uni(repr(seed), 'epoch', 'device', "'setup'")}) / (2 * tau / {rho!r}) AS setup_s,
         {sends('up')} * {wire!r} / 5e6 AS up_s, {sends('down')} * {wire!r} / 10e6 AS down_s
  FROM fleet, (SELECT range::INT AS epoch FROM range(1, {epochs + 1}))
), latency AS (SELECT *, comp_s + setup_s + up_s + down_s AS total_s FROM lat),
ranked AS (SELECT *, row_number() OVER (PARTITION BY epoch ORDER BY total_s, device)::INT AS place FROM latency)"""


def sharing_times(alphas, d: int, c: int, seed: str, k: int = 48) -> str:
    """``(alpha, device, share_s, encode_s)`` over ``fleet``."""
    one = (d * (d + 1) // 2 + d * c) * k * 1.1
    s = lambda kind: f"greatest(1.0, ceil(ln({uni(repr(seed), 'alpha', 'device', repr(kind))}) / ln(0.1)))"
    u = uni(repr(seed), "alpha", "device", "'encode'")
    return f"""SELECT alpha, device, greatest((alpha - 1) * {s('share-up')} * {one!r} / 5e6, (alpha - 1) * {s('share-down')} * {one!r} / 10e6) AS share_s,
alpha * {float(d * d + d * c)!r} / tau * (1 - ln({u}) / 2) AS encode_s FROM fleet, (SELECT unnest({list(alphas)})::INT AS alpha)"""


def planted_trace(epochs: int, alphas, keep: int, mu: float, lam: float, seed: str) -> str:
    """Common tables up to ``trace(scheme, alpha, epoch, elapsed_s, loss, accuracy)``: descent on planted classes written out as a recursion.

    All coded schemes share the trajectory of plain descent on all rows (that is what is claimed of them); only their clocks differ.
    """
    d, c, batches = 64, 10, 5
    rho = float(d * d * c)
    draw = lambda kind: f"greatest(1.0, ceil(ln({uni(repr(seed), 'epoch', 'device', repr(kind))}) / ln(0.1)))"
    server = lambda a: (25 - int(a) + 1) * (d * d * c + d * c) / 8.24e12
    schemes = [("conventional", 1, "mini", 25, 0.0), ("conventional_full", 1, "full", 25, 0.0), ("drop_slowest", 5, "full", keep, 0.0)]
    schemes += [("coded", a, "coded", 25 - a + 1, server(a)) for a in alphas]
    listed = ", ".join(f"('{s}', {a}, '{k}', {n}, {x!r})" for s, a, k, n, x in schemes)
    return f"""RECURSIVE {fleet()},
pts AS (SELECT vec_id, embedding, (list_position(embedding[1:10], list_max(embedding[1:10])) - 1)::INT AS cls FROM embeddings),
train AS (SELECT *, (ntile(25) OVER (ORDER BY cls, vec_id) - 1)::INT AS device, ({prf("'batch'", 'vec_id')} % {batches})::INT AS batch FROM pts WHERE vec_id % 5 <> 0),
test AS (SELECT vec_id, cls, [v::DOUBLE FOR v IN embedding] AS x FROM pts WHERE vec_id % 5 = 0),
dims AS (SELECT range::INT AS i FROM range({d})), outs AS (SELECT range::INT AS j FROM range({c})),
cells AS (SELECT device, batch, vec_id, cls, i, embedding[i + 1]::DOUBLE AS a FROM train, dims),
gram AS MATERIALIZED (SELECT l.device, l.batch, l.i, r.i AS j, sum(l.a * r.a) AS v FROM cells l JOIN cells r USING (vec_id) GROUP BY ALL),
crs AS MATERIALIZED (SELECT device, batch, i, cls AS j, sum(a) AS v FROM cells GROUP BY ALL),
kinds AS (SELECT 'coded' AS kind, {rho!r} AS rho, {d * c * 48 * 1.1!r} AS wire UNION ALL SELECT 'full', {rho!r}, {d * c * 32 * 1.1!r}
  UNION ALL SELECT 'mini', 2.0 * greatest(1, (SELECT count(*) FROM train) // {25 * batches}) * {d * c}, {d * c * 32 * 1.1!r}),
timed AS (SELECT kind, epoch, device, rho / tau - ln({uni(repr(seed), 'epoch', 'device', "'setup'")}) / (2 * tau / rho) + {draw('up')} * wire / 5e6 + {draw('down')} * wire / 10e6 AS total_s
  FROM fleet, kinds, (SELECT range::INT AS epoch FROM range(1, {epochs + 1}))),
placed AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY kind, epoch ORDER BY total_s, device)::INT AS place FROM timed),
kept AS (SELECT epoch, device FROM placed WHERE kind = 'full' AND place <= {keep}),
sets AS (SELECT 'all' AS walk, 0 AS e, device, batch FROM (SELECT DISTINCT device, batch FROM train)
  UNION ALL SELECT 'mini', batch, device, batch FROM (SELECT DISTINCT device, batch FROM train)
  UNION ALL SELECT 'drop', epoch, device, batch FROM kept JOIN (SELECT DISTINCT device, batch FROM train) USING (device)),
sizes AS (SELECT walk, e, count(*)::DOUBLE AS m FROM sets JOIN train USING (device, batch) GROUP BY ALL),
gsum AS (SELECT walk, e, i, j, sum(v) AS v FROM sets JOIN gram USING (device, batch) GROUP BY ALL),
grows AS (SELECT walk, e, i, list(v ORDER BY j) AS line FROM gsum GROUP BY ALL),
mats AS MATERIALIZED (SELECT walk, e, list(line ORDER BY i) AS g, any_value(m) AS m FROM grows JOIN sizes USING (walk, e) GROUP BY ALL),
hsum AS (SELECT walk, e, i, j, sum(v) AS v FROM sets JOIN crs USING (device, batch) GROUP BY ALL),
vecs AS MATERIALIZED (SELECT s.walk, s.e, o.j, list(coalesce(h.v, 0.0) ORDER BY x.i) AS h FROM sizes s, dims x, outs o LEFT JOIN hsum h ON h.walk = s.walk AND h.e = s.e AND h.i = x.i AND h.j = o.j GROUP BY ALL),
path(walk, epoch, j, theta) AS (
  SELECT walk, 0, j, [0.0::DOUBLE FOR k IN range({d})] FROM (SELECT DISTINCT walk FROM mats), outs
  UNION ALL
  SELECT p.walk, p.epoch + 1, p.j, [p.theta[k] - {mu!r} * ((list_dot_product(a.g[k], p.theta) - b.h[k]) / a.m + {lam!r} * p.theta[k]) FOR k IN range(1, {d + 1})]
  FROM path p JOIN mats a ON a.walk = p.walk AND a.e = CASE p.walk WHEN 'all' THEN 0 WHEN 'mini' THEN p.epoch % {batches} ELSE p.epoch + 1 END
  JOIN vecs b ON b.walk = a.walk AND b.e = a.e AND b.j = p.j WHERE p.epoch < {epochs}),
losses AS (SELECT p.walk, p.epoch, (sum(list_dot_product(p.theta, [list_dot_product(line, p.theta) FOR line IN a.g])) - 2 * sum(list_dot_product(p.theta, b.h)) + any_value(a.m)) / (2 * any_value(a.m))
  + {lam / 2!r} * sum(list_dot_product(p.theta, p.theta)) AS loss FROM path p JOIN mats a ON a.walk = 'all' JOIN vecs b ON b.walk = 'all' AND b.j = p.j GROUP BY ALL),
answers AS (SELECT walk, epoch, vec_id, cls, arg_min(j, (-list_dot_product(x, theta), j)) AS predicted FROM path, test WHERE epoch > 0 GROUP BY ALL),
scored AS (SELECT walk, epoch, avg((predicted = cls)::INT) AS accuracy FROM answers GROUP BY ALL),
schemes(scheme, alpha, kind, keep, server_s) AS (VALUES {listed}),
shared AS ({sharing_times(alphas, d, c, seed)}),
offsets AS (SELECT alpha, max(share_s + encode_s) AS off FROM shared GROUP BY 1),
epochs AS (SELECT scheme, alpha, epoch, max(total_s) + any_value(server_s) AS seconds FROM schemes JOIN placed USING (kind) WHERE place <= keep GROUP BY ALL),
clock AS (SELECT scheme, alpha, epoch, CASE WHEN scheme = 'coded' THEN (SELECT off FROM offsets o WHERE o.alpha = q.alpha) ELSE 0 END + sum(seconds) OVER (PARTITION BY scheme, alpha ORDER BY epoch) AS elapsed_s FROM epochs q),
trace AS MATERIALIZED (SELECT scheme, alpha, epoch, elapsed_s, loss, accuracy FROM clock JOIN scored USING (epoch) JOIN losses USING (walk, epoch)
  WHERE walk = CASE scheme WHEN 'conventional' THEN 'mini' WHEN 'drop_slowest' THEN 'drop' ELSE 'all' END)"""
