"""DuckDB SQL for the method queries, written apart from the DataFrame plans."""

from __future__ import annotations

import math

from hushgrad.plans.native import D, N, OTHER, S, START

TWO_PI = repr(2.0 * math.pi)


def u(*parts: str) -> str:
    """Digest uniform; parts are SQL texts."""
    joined = ", ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"(CAST('0x' || substr(md5(concat_ws('|', {joined})), 1, 13) AS BIGINT) / 4503599627370496.0)"


def normal(*parts: str) -> str:
    return f"round(sqrt(-2.0 * ln(1.0 - {u(chr(39) + 'radius' + chr(39), *parts)})) * cos({TWO_PI} * {u(chr(39) + 'angle' + chr(39), *parts)}), 9)"


SAMPLES = f"""samples AS (
  SELECT CAST(l_suppkey % {N} AS INTEGER) AS client_id,
         concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber) AS sample_id,
         [(l_quantity / 50.0) * 0.4, (l_extendedprice / 110000.0) * 0.4, (l_discount * 10.0) * 0.4, (l_tax * 12.5) * 0.4,
          (CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE 0.0 END)::DOUBLE * 0.4, 1.0::DOUBLE * 0.4]::DOUBLE[] AS f,
         (CASE WHEN (l_quantity / 50.0) + (l_discount * 10.0) - (l_tax * 12.5) > 0.5 THEN 1.0 ELSE -1.0 END)::DOUBLE AS y
  FROM lineitem)"""


def vec(values: list[float]) -> str:
    return "([" + ", ".join(repr(float(v)) for v in values) + "]::DOUBLE[])"


def dot(a: str, b: str) -> str:
    return "(0.0::DOUBLE" + "".join(f" + {a}[{i}] * {b}[{i}]" for i in range(1, D + 1)) + ")"


def grad(x: str) -> str:
    w = f"(-y / (1.0::DOUBLE + exp(y * {dot('f', x)})))"
    lam = repr(2 * S.lam)
    return "[" + ", ".join(f"{w} * f[{i}] + {lam}::DOUBLE * {x}[{i}] / ((1.0 + {x}[{i}] * {x}[{i}]) * (1.0 + {x}[{i}] * {x}[{i}]))" for i in range(1, D + 1)) + "]"


def norm(g: str) -> str:
    return "sqrt(0.0::DOUBLE" + "".join(f" + {g}[{i}] * {g}[{i}]" for i in range(1, D + 1)) + ")"


def clip(g: str, n: str) -> str:
    return f"list_transform({g}, lambda v: v * (CASE WHEN {n} > {S.clip!r} THEN {S.clip!r} / {n} ELSE 1.0 END))"


def total(v: str) -> str:
    return f"(sum(CAST(round(({v}) * 1000000000.0) AS BIGINT))::DOUBLE / 1000000000.0)"


def batch(t: int, source: str = "samples") -> str:
    draw = u("'batch'", str(S.seed), str(t), "client_id", "sample_id")
    return f"(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY {draw}, sample_id) AS rk FROM {source}) WHERE rk <= {S.b})"


def spread(source: str, column: str) -> str:
    return f"(SELECT client_id, unnest(range({D}))::INTEGER AS coord, unnest({column}) AS v FROM {source})"


def masked(source: str, t: int) -> str:
    draw = u("'mask'", str(S.seed), str(t), "client_id", "coord")
    return (
        f"(SELECT client_id, coord, round(value * {float(D)!r} / {float(S.k)!r}, 9) AS value FROM "
        f"(SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY {draw}, coord) AS rk FROM {source}) WHERE rk <= {S.k})"
    )


def noise(t: int) -> str:
    return normal("'noise'", str(S.seed), str(t), "client_id", "coord")


def rounds(count: int, shifted: bool, squeeze: bool = True) -> str:
    """WITH list of `count` rounds: tables msg0.. and x0..x{count}, ref0.."""
    out = [SAMPLES, f"x0 AS (SELECT {vec(START)} AS x)", f"ref0 AS (SELECT {vec([0.0] * D)} AS ref)"]
    for t in range(count):
        out.append(f"g{t} AS (SELECT client_id, {grad('x')} AS g FROM {batch(t)}, x{t})")
        out.append(f"c{t} AS (SELECT client_id, {clip('g', 'nrm')} AS g FROM (SELECT *, {norm('g')} AS nrm FROM g{t}))")
        out.append(f"p{t} AS (SELECT client_id, coord, {total('v')} / {float(S.b)!r} AS value FROM {spread(f'c{t}', 'g')} GROUP BY ALL)")
        out.append(f"n{t} AS (SELECT client_id, coord, round(value + {S.sigma!r} * {noise(t)}, 9) AS value FROM p{t})")
        source = f"n{t}"
        if shifted and t:
            out.append(
                f"z{t} AS (SELECT n.client_id, n.coord, round(n.value - coalesce(s.shift, 0.0), 9) AS value FROM n{t} n "
                f"LEFT JOIN s{t} s ON n.client_id = s.client_id AND n.coord = s.coord)"
            )
            source = f"z{t}"
        out.append(f"msg{t} AS (SELECT * FROM {masked(source, t) if squeeze else source})")
        out.append(f"mean{t} AS (SELECT coord, {total('value')} / {float(N)!r} AS mean FROM msg{t} GROUP BY coord)")
        base = (
            f"(SELECT r.coord, x[r.coord + 1] AS xv, ref[r.coord + 1] AS rv, coalesce(mean, 0.0) AS mean "
            f"FROM (SELECT unnest(range({D}))::INTEGER AS coord) r CROSS JOIN x{t} CROSS JOIN ref{t} LEFT JOIN mean{t} USING (coord))"
        )
        out.append(f"x{t + 1} AS (SELECT list(round(xv - {S.eta!r} * (rv + mean), 9) ORDER BY coord) AS x FROM {base})")
        if shifted:
            out.append(f"ref{t + 1} AS (SELECT list(round(rv + {S.gamma!r} * mean, 9) ORDER BY coord) AS ref FROM {base})")
            new = f"SELECT client_id, coord, round({S.gamma!r} * value, 9) AS shift FROM msg{t}"
            if t:
                new = f"SELECT client_id, coord, round({total('shift')}, 9) AS shift FROM (SELECT * FROM s{t} UNION ALL {new}) GROUP BY ALL"
            out.append(f"s{t + 1} AS ({new})")
        else:
            out.append(f"ref{t + 1} AS (SELECT ref FROM ref{t})")
    return "WITH " + ",\n".join(out)


def visited(count: int) -> str:
    rows = [f"SELECT {t} AS round, unnest(range({D}))::INTEGER AS coord, unnest(x) AS v FROM x{t}" for t in range(count + 1)]
    return "SELECT round, coord, v AS value FROM (" + " UNION ALL ".join(rows) + ")"


def last_round(t: int) -> str:
    """SAGA table as a chain of tables tab1..tab{t}; returns its WITH entries."""
    out = ["tab1 AS (SELECT *, 0 AS last_round FROM samples)"]
    for r in range(1, t):
        out.append(
            f"tab{r + 1} AS (SELECT a.* REPLACE (CASE WHEN b.sample_id IS NOT NULL THEN {r} ELSE a.last_round END AS last_round) "
            f"FROM tab{r} a LEFT JOIN {batch(r)} b ON a.sample_id = b.sample_id AND a.client_id = b.client_id)"
        )
    return ",\n".join(out)


def difference(t: int, source: str, x: str, w: str) -> str:
    """Estimates of round t: batch difference of gradients at x and w, plus the mean gradient at w over all rows."""
    return f"""
pair AS (SELECT *, {grad(x)} AS g1, {grad(w)} AS g2 FROM {source}),
cut AS (SELECT client_id, sample_id, {clip('g1', 'n1')} AS gx, {clip('g2', 'n2')} AS gw FROM (SELECT *, {norm('g1')} AS n1, {norm('g2')} AS n2 FROM pair)),
diff AS (SELECT client_id, coord, {total('v')} / {float(S.b)!r} AS value FROM
  (SELECT client_id, unnest(range({D}))::INTEGER AS coord, unnest([{', '.join(f'gx[{i}] - gw[{i}]' for i in range(1, D + 1))}]) AS v FROM {batch(t, 'cut')}) GROUP BY ALL),
m AS (SELECT client_id, count(*) AS m FROM samples GROUP BY 1),
fullg AS (SELECT client_id, coord, {total('v')} / m AS full_value FROM {spread('cut', 'gw')} JOIN m USING (client_id) GROUP BY client_id, coord, m)
SELECT client_id, coord, round(value + full_value, 6) AS value FROM diff JOIN fullg USING (client_id, coord)"""


def snapshot_of(t: int) -> int:
    """The coins of `svrg_refresh` with probability 0.5: the last round before t that moved the snapshot, else 0."""
    import hashlib

    coin = lambda r: int(hashlib.md5(f"coin|{S.seed}|{r}".encode()).hexdigest()[:13], 16) / 4503599627370496
    moved = [r for r in range(t) if coin(r) < 0.5]
    return moved[-1] if moved else 0


def reduced(count: int, kind: str, shifted: bool, squeeze: bool) -> str:
    """WITH list of `count` rounds whose estimate is a batch difference plus a full gradient, at the models visited."""
    out = [SAMPLES, f"x0 AS (SELECT {vec(START)} AS x)", f"ref0 AS (SELECT {vec([0.0] * D)} AS ref)", last_round(max(1, count - 1)), "m AS (SELECT client_id, count(*) AS m FROM samples GROUP BY 1)"]
    for t in range(count):
        if kind == "svrg":
            source = f"(SELECT s.*, a.x AS x, b.x AS w FROM samples s CROSS JOIN x{t} a CROSS JOIN x{snapshot_of(t)} b)"
        else:
            had = max(t, 1)
            cases = " ".join(f"WHEN {r} THEN p{r}.x" for r in range(had))
            source = f"(SELECT s.* EXCLUDE (last_round), a.x AS x, CASE last_round {cases} END AS w FROM tab{had} s CROSS JOIN x{t} a " + " ".join(f"CROSS JOIN x{r} p{r}" for r in range(had)) + ")"
        out.append(f"pr{t} AS (SELECT *, {grad('x')} AS g1, {grad('w')} AS g2 FROM {source})")
        out.append(f"cu{t} AS (SELECT client_id, sample_id, {clip('g1', 'n1')} AS gx, {clip('g2', 'n2')} AS gw FROM (SELECT *, {norm('g1')} AS n1, {norm('g2')} AS n2 FROM pr{t}))")
        minus = ", ".join(f"gx[{i}] - gw[{i}]" for i in range(1, D + 1))
        out.append(f"di{t} AS (SELECT client_id, coord, {total('v')} / {float(S.b)!r} AS value FROM (SELECT client_id, unnest(range({D}))::INTEGER AS coord, unnest([{minus}]) AS v FROM {batch(t, f'cu{t}')}) GROUP BY ALL)")
        out.append(f"fu{t} AS (SELECT client_id, coord, {total('v')} / 1.0 / m AS full_value FROM {spread(f'cu{t}', 'gw')} JOIN m USING (client_id) GROUP BY client_id, coord, m)")
        out.append(f"n{t} AS (SELECT client_id, coord, round(value + full_value + {S.sigma!r} * {noise(t)}, 9) AS value FROM di{t} JOIN fu{t} USING (client_id, coord))")
        sent = f"n{t}"
        if shifted and t:
            out.append(f"z{t} AS (SELECT n.client_id, n.coord, round(n.value - coalesce(s.shift, 0.0), 9) AS value FROM n{t} n LEFT JOIN s{t} s ON n.client_id = s.client_id AND n.coord = s.coord)")
            sent = f"z{t}"
        out.append(f"msg{t} AS (SELECT * FROM {masked(sent, t) if squeeze else sent})")
        out.append(f"mean{t} AS (SELECT coord, {total('value')} / {float(N)!r} AS mean FROM msg{t} GROUP BY coord)")
        base = f"(SELECT r.coord, x[r.coord + 1] AS xv, ref[r.coord + 1] AS rv, coalesce(mean, 0.0) AS mean FROM (SELECT unnest(range({D}))::INTEGER AS coord) r CROSS JOIN x{t} CROSS JOIN ref{t} LEFT JOIN mean{t} USING (coord))"
        out.append(f"x{t + 1} AS (SELECT list(round(xv - {S.eta!r} * (rv + mean), 9) ORDER BY coord) AS x FROM {base})")
        if shifted:
            out.append(f"ref{t + 1} AS (SELECT list(round(rv + {S.gamma!r} * mean, 9) ORDER BY coord) AS ref FROM {base})")
            new = f"SELECT client_id, coord, round({S.gamma!r} * value, 9) AS shift FROM msg{t}"
            if t:
                new = f"SELECT client_id, coord, round({total('shift')}, 9) AS shift FROM (SELECT * FROM s{t} UNION ALL {new}) GROUP BY ALL"
            out.append(f"s{t + 1} AS ({new})")
        else:
            out.append(f"ref{t + 1} AS (SELECT ref FROM ref{t})")
    return "WITH " + ",\n".join(out)


def distance(a: str, b: str) -> str:
    return "(0.0::DOUBLE" + "".join(f" + ({a}[{i}] - {b}[{i}]) * ({a}[{i}] - {b}[{i}])" for i in range(1, D + 1)) + ")"


SQL: dict[str, str] = {
    "shifted_svrg_round": reduced(3, "svrg", True, True) + " " + visited(3),
    "shifted_saga_round": reduced(3, "saga", True, True) + " " + visited(3),
    "ldp_svrg_round": reduced(2, "svrg", False, False) + " " + visited(2),
    "drift_svrg": reduced(3, "svrg", True, True) + " " + " UNION ALL ".join(f"SELECT {t} AS round, round({distance('a.x', 'b.x')}, 9) AS drift FROM x{t} a, x{snapshot_of(t)} b" for t in range(3)),
    "max_row_norm": f"WITH {SAMPLES}, v AS (SELECT max({dot('f', 'f')}) AS v FROM samples) SELECT round(v, 9) AS max_sq_norm, round(v / 4 + {2 * S.lam!r}, 9) AS smoothness FROM v",
    "shift_cogroup": rounds(3, True) + " SELECT client_id, coord, shift FROM s3",
    "loss_at_point": f"""WITH {SAMPLES},
  each AS (SELECT client_id, ln(1.0 + exp(-y * {dot('f', vec(START))})) AS l FROM samples),
  per AS (SELECT client_id, {total('l')} / count(*) AS l FROM each GROUP BY 1)
  SELECT round({total('l')} / count(*) + {sum(S.lam * v * v / (1 + v * v) for v in START)!r}, 6) AS loss FROM per""",
    "full_gradient": f"""WITH {SAMPLES}, g AS (SELECT client_id, {grad(vec(START))} AS g FROM samples),
  m AS (SELECT client_id, count(*) AS m FROM samples GROUP BY 1),
  per AS (SELECT client_id, coord, {total('v')} / m AS value FROM {spread('g', 'g')} JOIN m USING (client_id) GROUP BY client_id, coord, m)
  SELECT coord, round({total('value')} / count(*), 6) AS value FROM per GROUP BY 1""",
    "clipped_gradient": f"""WITH {SAMPLES}, g AS (SELECT client_id, {grad(vec(START))} AS g FROM samples),
  n AS (SELECT *, {norm('g')} AS nrm FROM g), c AS (SELECT client_id, {clip('g', 'nrm')} AS g FROM n),
  w AS (SELECT client_id, count(*) AS m, sum(CASE WHEN nrm > {S.clip!r} THEN 1 ELSE 0 END) AS cut FROM n GROUP BY 1)
  SELECT client_id, coord, round({total('v')} / m, 6) AS value, CAST(cut AS BIGINT) AS n_clipped FROM {spread('c', 'g')} JOIN w USING (client_id) GROUP BY client_id, coord, m, cut""",
    "minibatch_pick": f"WITH {SAMPLES} SELECT client_id, sample_id, rk AS rank_in_client FROM {batch(1)}",
    "noise_draws": f"""SELECT client_id, coord, {noise(0)} AS noise
  FROM (SELECT DISTINCT l_suppkey AS client_id FROM lineitem) CROSS JOIN (SELECT unnest(range(50)) AS coord)""",
    "randk_message": rounds(1, False) + " SELECT client_id, coord, value FROM msg0",
    "randk_pick": rounds(1, False) + " SELECT client_id, count(*) AS kept, CAST(sum(coord) AS BIGINT) AS coord_sum FROM msg0 GROUP BY 1",
    "quantized_message": rounds(1, False) + f""", q AS (SELECT client_id, sqrt({total('value * value')}) AS n FROM n0 GROUP BY 1),
  x AS (SELECT client_id, coord, value, n, abs(value) / n * 4.0 AS lv, {u("'level'", str(S.seed), '0', 'client_id', 'coord')} AS du FROM n0 JOIN q USING (client_id))
  SELECT client_id, coord, round(sign(value) * (floor(lv) + CASE WHEN du < lv - floor(lv) THEN 1.0 ELSE 0.0 END) * n / 4.0, 9) AS value FROM x""",
    "direct_round": rounds(1, False) + " " + visited(1),
    "ldp_sgd_round": rounds(1, False, False) + " " + visited(1),
    "shifted_round": rounds(1, True) + " SELECT client_id, coord, shift FROM s1",
    "two_round_direct": rounds(2, False) + " " + visited(2),
    "three_round_shifted": rounds(3, True) + " " + visited(3),
    "shift_update": rounds(3, True) + " SELECT client_id, coord, shift FROM s3",
    "shift_mismatch": rounds(3, True) + f""", fg AS (SELECT client_id, {grad(vec(START))} AS g FROM samples), m AS (SELECT client_id, count(*) AS m FROM samples GROUP BY 1),
  per AS (SELECT client_id, coord, {total('v')} / m AS value FROM {spread('fg', 'g')} JOIN m USING (client_id) GROUP BY client_id, coord, m)
  SELECT round({total('(value - coalesce(shift, 0.0)) * (value - coalesce(shift, 0.0))')} / {float(N)!r}, 6) AS mismatch FROM per LEFT JOIN s3 USING (client_id, coord)""",
    "server_mean": rounds(1, False) + " SELECT coord, round(mean, 6) AS mean FROM mean0",
    "comm_bits": rounds(2, False) + f""", a AS (SELECT 0 AS round, count(*) AS sent FROM msg0 UNION ALL SELECT 1, count(*) FROM msg1)
  SELECT round, sent, CAST(32 * sent AS BIGINT) AS value_bits, CAST(3 * sent AS BIGINT) AS index_bits, CAST(sum(32 * sent) OVER (ORDER BY round) AS BIGINT) AS total_value_bits FROM a""",
    "svrg_estimate": f"WITH {SAMPLES}," + difference(2, "samples", vec(OTHER), vec(START)),
    "saga_refresh": f"WITH {SAMPLES}, {last_round(4)} SELECT client_id, last_round, count(*) AS samples FROM tab4 GROUP BY ALL",
    "saga_estimate": f"WITH {SAMPLES}, {last_round(3)}, tw AS (SELECT *, [{vec(START)}, {vec(OTHER)}, {vec([0.5 * v for v in START])}][last_round + 1] AS w FROM tab3),"
    + difference(3, "tw", vec([0.2] * D), "w"),
    "drift_saga": f"""WITH {SAMPLES}, {last_round(3)},
  d AS (SELECT last_round, count(*) AS c FROM tab3 GROUP BY 1)
  SELECT round(sum(c * [{', '.join(repr(sum((0.2 - v) ** 2 for v in w)) for w in (START, OTHER, [0.5 * v for v in START]))}][last_round + 1]) / sum(c), 6) AS drift FROM d""",
    "svrg_refresh": f"SELECT r AS round, CAST({u(chr(39) + 'coin' + chr(39), str(S.seed), 'r')} < 0.2 AS BOOLEAN) AS moves FROM (SELECT DISTINCT date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS r FROM orders)",
    "compressor_error": f"""WITH {SAMPLES}, own AS (SELECT CAST(split_part(sample_id, '|', 3) AS BIGINT) AS client_id, f FROM samples), m AS (SELECT client_id, count(*) AS m FROM own GROUP BY 1),
  a AS (SELECT client_id, coord, round({total('v')} / m, 9) AS value FROM {spread('own', 'f')} JOIN m USING (client_id) GROUP BY client_id, coord, m),
  sq AS (SELECT client_id, {total('value * value')} AS sq FROM a GROUP BY 1),
  kept AS (SELECT * FROM {masked('a', 0)}),
  err AS (SELECT a.client_id, {total('(coalesce(k.value, 0.0) - a.value) * (coalesce(k.value, 0.0) - a.value)')} / any_value(sq) AS e FROM a JOIN sq USING (client_id) LEFT JOIN kept k ON a.client_id = k.client_id AND a.coord = k.coord GROUP BY 1)
  SELECT round({total('e')} / count(*), 6) AS mean_error, {D / S.k - 1!r} AS omega FROM err""",
    "dot_products": f"WITH {SAMPLES} SELECT client_id, round({total(dot('f', vec(START)))}, 4) AS margin_sum, count(*) AS n FROM samples GROUP BY 1",
    "clip_vectors": f"""WITH {SAMPLES}, n AS (SELECT client_id, {norm('f')} AS nrm FROM samples)
  SELECT client_id, round({total(f'CASE WHEN nrm > {S.clip!r} THEN {S.clip!r} / nrm ELSE 1.0 END')}, 4) AS scale_sum, CAST(sum(CASE WHEN nrm > {S.clip!r} THEN 1 ELSE 0 END) AS BIGINT) AS n_clipped FROM n GROUP BY 1""",
    "logistic_grad": f"WITH {SAMPLES}, g AS (SELECT client_id, sample_id, {grad(vec(START))} AS g FROM samples) SELECT client_id, sample_id, round({norm('g')}, 6) AS grad_norm FROM g",
    "active_clients": rounds(2, False) + " SELECT coord, count(DISTINCT client_id) AS clients, count(*) AS messages FROM (SELECT * FROM msg0 UNION ALL SELECT * FROM msg1) GROUP BY 1",
    "batch_overlap": f"""WITH {SAMPLES}, a AS (SELECT client_id, sample_id FROM {batch(0)}), b AS (SELECT client_id, sample_id FROM {batch(1)})
  SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL
  SELECT 'first_only', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)""",
    "vector_long": rounds(1, False) + " SELECT client_id, list(value ORDER BY coord)[1] AS first_value, count(*) AS n FROM msg0 GROUP BY 1",
    "topk_shift_coords": rounds(3, True) + """ SELECT client_id, coord, shift FROM
  (SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY abs(shift) DESC, coord) AS r FROM s3) WHERE r <= 2""",
    "grad_norm_profile": f"""WITH {SAMPLES}, g AS (SELECT client_id, {grad(vec(START))} AS g FROM samples), n AS (SELECT client_id, round({norm('g')}, 6) AS v FROM g)
  SELECT client_id, round(avg(v), 4) AS mean_norm, round(stddev_pop(v), 4) AS sd_norm, round(quantile_cont(v, 0.5), 4) AS median_norm, round(quantile_cont(v, 0.9), 4) AS p90_norm FROM n GROUP BY 1""",
}
