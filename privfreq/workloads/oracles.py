"""The queries' results as SQL for another engine, written from the definitions and not from the Spark plans."""

from __future__ import annotations

import math

from ..params import COIN, P31, SMALL, Params, threshold

WORDS = SMALL.but(m=256, k=16)
COUNT = SMALL.but(m=512, k=5)
AUDIT = SMALL.but(m=3, k=1, eps=2.0)
#: Points of the experiments' grids that are checked bit by bit, on small sketches.
GRIDS = {"eps": tuple(float(e) for e in range(1, 8)), "r": (0.1, 0.15, 0.2, 0.25, 0.3), "theta": (0.3, 0.35, 0.4, 0.45, 0.5, 0.55, 0.6), "k": (2, 4, 8, 16, 32), "m": (16, 32, 64, 128, 256)}


def num(x: float) -> str:
    text = repr(float(x))
    return f"CAST('{text}' AS DOUBLE)"


def str_key(x: str) -> str:
    return f"(('0x' || substr(md5({x}), 1, 15))::BIGINT % {P31})"


def coin(rid: str, p: Params, tag: str, i: str = "0", slot: str = "0") -> str:
    return f"('0x' || substr(md5({rid} || '|{p.seed}|{tag}|' || {i}), 1 + 7 * ({slot}), 7))::BIGINT"


def uniform(rid: str, p: Params, tag: str, n: int) -> str:
    return f"(({coin(rid, p, tag)} * {n}) // {COIN})"


def hashes(name: str, table: list[tuple[int, int]]) -> str:
    return f"{name}(j, a, b) AS (VALUES {', '.join(f'({j}, {a}::BIGINT, {b}::BIGINT)' for j, (a, b) in enumerate(table))})"


def place(key: str, width: int, t: str = "hp") -> str:
    return f"((({t}.a * {key} + {t}.b) % {P31}) % {width})"


def split_words(table: str, *ids: str) -> str:
    names = ", ".join(ids)
    rid = " || '|' || ".join([*ids, "pos"])
    return f"""SELECT {rid} AS rid, item, {str_key('item')} AS key, {names} FROM (SELECT {names}, unnest(generate_series(0, len(w) - 1)) AS pos, unnest(w) AS item
      FROM (SELECT {names}, string_split_regex(lower(text), '[ \\t\\n\\r]+') AS w FROM {table})) WHERE item <> ''"""


LINE = "l_orderkey || '|' || l_partkey || '|' || l_suppkey || '|' || l_linenumber"
CLIENTS = {
    "words": split_words("documents", "doc_id"),
    "chat_words": split_words("conversations", "conv_id", "turn"),
    "parts": f"SELECT {LINE} AS rid, l_partkey AS item, l_partkey % {P31} AS key FROM lineitem",
    "customers": f"SELECT o_orderkey::VARCHAR AS rid, o_custkey AS item, o_custkey % {P31} AS key FROM orders",
    "types": f"SELECT event_id::VARCHAR AS rid, event_type AS item, {str_key('event_type')} AS key FROM events",
    "sensor_fine": f"SELECT event_id::VARCHAR AS rid, round(value * 100)::BIGINT AS item, ((round(value * 100)::BIGINT % {P31}) + {P31}) % {P31} AS key FROM events",
    "sensor_coarse": f"SELECT event_id::VARCHAR AS rid, round(value * 10)::BIGINT AS item, ((round(value * 10)::BIGINT % {P31}) + {P31}) % {P31} AS key FROM events",
    "props": f"SELECT event_id::VARCHAR AS rid, json_extract_string(props, '$.k')::BIGINT AS item, json_extract_string(props, '$.k')::BIGINT % {P31} AS key FROM events",
    "users": f"SELECT event_id::VARCHAR AS rid, user_id AS item, user_id % {P31} AS key FROM events",
    "hosts": f"SELECT page_id::VARCHAR AS rid, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS item, {str_key(chr(39) + chr(39))} AS key FROM pages",
}


def base(name: str) -> str:
    return f"c AS ({CLIENTS[name]}), truth AS (SELECT item, count(*)::BIGINT AS f FROM c GROUP BY item), d AS (SELECT DISTINCT item, key FROM c)"


def phase(p: Params) -> str:
    return f"ph AS (SELECT *, CASE WHEN {coin('rid', p, 'phase')} < {threshold(p.r)} THEN 1 ELSE 2 END AS phase FROM c)"


def one_hot(source: str, p: Params, out: str = "st", heavy: str = "FALSE") -> str:
    """CTEs that make the state `out` of the clients in `source` (rid, key, and what heavy needs)."""
    return f"""{out}_r AS (SELECT rid, key, {heavy} AS heavy, {uniform('rid', p, 'row', p.k)} AS j FROM {source}),
    {out}_p AS (SELECT rid, r.j AS j, CASE WHEN heavy THEN -1 ELSE {place('key', p.m)} END AS pos FROM {out}_r r JOIN hp ON hp.j = r.j),
    {out}_w AS (SELECT j, pos, i, md5(rid || '|{p.seed}|bit|' || i) AS word FROM {out}_p, generate_series(0, {p.m // 4 - 1}) t(i)),
    {out}_b AS (SELECT j, i * 4 + s AS b, pos, ('0x' || substr(word, 1 + 7 * s, 7))::BIGINT AS u FROM {out}_w, (VALUES (0), (1), (2), (3)) v(s)),
    {out} AS (SELECT j, b, sum(CASE WHEN (b = pos) <> (u < {threshold(p.q)}) THEN 1 ELSE 0 END)::BIGINT AS plus, count(*)::BIGINT AS reports FROM {out}_b GROUP BY j, b)"""


def sums(p: Params, state: str = "st") -> str:
    return f"""{state}_n AS (SELECT coalesce(sum(n), 0)::BIGINT AS n FROM (SELECT max(reports) AS n FROM {state} GROUP BY j)),
    {state}_s AS (SELECT d.item, coalesce(sum(2 * s.plus - s.reports), 0)::BIGINT AS s1 FROM d CROSS JOIN hp LEFT JOIN {state} s ON s.j = hp.j AND s.b = {place('d.key', p.m)} GROUP BY d.item)"""


def value(p: Params, mass: str = "n") -> str:
    return f"({num(p.m / (p.m - 1))} * (({num(p.c)} * s1 + n) / 2 - {mass} / {p.m}) + 0)"


def one_hot_estimate(name: str, p: Params) -> str:
    return f"{base(name)}, {hashes('hp', p.hashes())}, {one_hot('c', p)}, {sums(p)}, est AS (SELECT item, {value(p)} AS f_hat FROM st_s, st_n)"


def hadamard(name: str, p: Params) -> str:
    sign = f"CASE WHEN {coin('rid', p, 'flip')} < {threshold(p.hadamard_q)} THEN -1 ELSE 1 END * (1 - 2 * (bit_count(l & {place('key', p.m)}) % 2))"
    return f"""{base(name)}, {hashes('hp', p.hashes())}, dr AS (SELECT rid, key, {uniform('rid', p, 'row', p.k)} AS j, {uniform('rid', p, 'coordinate', p.m)} AS l FROM c),
    st AS (SELECT dr.j, l, sum({sign})::BIGINT AS signed_sum, count(*)::BIGINT AS reports FROM dr JOIN hp ON hp.j = dr.j GROUP BY dr.j, l)"""


def hadamard_estimate(name: str, p: Params) -> str:
    return f"""{hadamard(name, p)}, inv AS (SELECT j, t.b, sum(signed_sum * (1 - 2 * (bit_count(l & t.b) % 2)))::BIGINT AS s FROM st, generate_series(0, {p.m - 1}) t(b) GROUP BY j, t.b),
    sm AS (SELECT d.item, coalesce(sum(inv.s), 0)::BIGINT AS s FROM d CROSS JOIN hp LEFT JOIN inv ON inv.j = hp.j AND inv.b = {place('d.key', p.m)} GROUP BY d.item),
    est AS (SELECT item, {num(p.m / (p.m - 1))} * ({num(p.hadamard_c)} * s - (SELECT sum(reports)::BIGINT FROM st) / {p.m}) + 0 AS f_hat FROM sm)"""


def local_hash(name: str, p: Params) -> str:
    y = place("key", p.g)
    return f"""{base(name)}, {hashes('hp', p.hashes(p.k_pool))}, dr AS (SELECT rid, key, {uniform('rid', p, 'row', p.k_pool)} AS j FROM c),
    rp AS (SELECT dr.j, CASE WHEN {coin('rid', p, 'keep')} < {threshold(p.keep)} THEN {y} ELSE ({y} + 1 + {uniform('rid', p, 'other', p.g - 1)}) % {p.g} END AS y FROM dr JOIN hp ON hp.j = dr.j),
    st AS (SELECT j, y, count(*)::BIGINT AS cnt FROM rp GROUP BY j, y)"""


def local_hash_estimate(name: str, p: Params) -> str:
    return f"""{local_hash(name, p)}, sm AS (SELECT d.item, coalesce(sum(st.cnt), 0)::BIGINT AS s FROM d CROSS JOIN hp LEFT JOIN st ON st.j = hp.j AND st.y = {place('d.key', p.g)} GROUP BY d.item),
    est AS (SELECT item, (s - (SELECT sum(cnt)::BIGINT FROM st) / {p.g}) / {num(p.keep - 1 / p.g)} + 0 AS f_hat FROM sm)"""


def counts(name: str, p: Params, signed: bool = False) -> str:
    both = f"{base(name)}, {hashes('hp', p.hashes())}, {hashes('sp', p.hashes(family='s'))}"
    sign = f"(1 - 2 * (((sp.a * d.key + sp.b) % {P31}) % 2))"
    at = f"pl AS (SELECT d.item, hp.j, {place('d.key', p.m)} AS b, {sign if signed else '1'} AS s, f FROM d JOIN truth USING (item) CROSS JOIN hp JOIN sp ON sp.j = hp.j)"
    return f"{both}, {at}, st AS (SELECT j, b, sum(f * s)::BIGINT AS cnt FROM pl GROUP BY j, b)"


def count_estimate(name: str, p: Params, how: str) -> str:
    signed = how in ("mean", "median")
    v = {"min": "min(st.cnt)::DOUBLE", "mean": f"sum(st.cnt * pl.s)::BIGINT / {p.k} + 0", "median": "median(st.cnt * pl.s)::DOUBLE + 0", "row": f"{num(p.m / (p.m - 1))} * (sum(st.cnt)::BIGINT / {p.k} - (SELECT sum(f)::BIGINT FROM truth) / {p.m}) + 0"}[how]
    return f"{counts(name, p, signed)}, est AS (SELECT pl.item, {v} AS f_hat FROM pl JOIN st ON st.j = pl.j AND st.b = pl.b GROUP BY pl.item)"


def boundary(scores: str, theta: float, total: str | None = None) -> str:
    """bd(p, prefix_len, total, realised) by a running sum over single items."""
    total = total or f"(SELECT sum(g) FROM {scores})"
    return f"""run AS (SELECT g, sum(g) OVER (ORDER BY g DESC, item ROWS UNBOUNDED PRECEDING) AS acc FROM {scores}),
    cut AS (SELECT coalesce(min(g), CAST('inf' AS DOUBLE)) AS p, count(*)::BIGINT AS prefix_len FROM run WHERE acc <= {num(theta)} * {total}),
    bd AS (SELECT p, prefix_len, (SELECT sum(g) FROM {scores}) AS total, coalesce((SELECT sum(g) FROM {scores} WHERE g >= p), 0) / (SELECT sum(g) FROM {scores}) AS realised FROM cut)"""


SCORES = "scores AS (SELECT item, f::DOUBLE AS g FROM truth)"


def split(name: str, p: Params, mass: str = "sketch", scale: str = "population", heavy: str = ">=") -> str:
    """est(item, f_hat, path) with true frequencies as scores."""
    mass_sql = {
        "nominal": f"({num(1 - p.theta)} * n)",
        "realised": "((1 - (SELECT realised FROM bd)) * n)",
        "sketch": f"(({num(p.c)} * (2 * (SELECT sum(plus)::BIGINT FROM st) - {p.m} * n) + {p.m} * n) / 2)",
    }[mass]
    light = value(p, mass_sql)
    first = ""
    if scale == "population":
        light = f"({light} / {num(1 - p.r)})"
    if scale == "pooled":
        first = f", {one_hot('ph1', p, 's1t')}, {sums(p, 's1t')}, e1 AS (SELECT item, {value(p)} AS f1 FROM s1t_s, s1t_n)"
        light = f"({light} + (SELECT f1 FROM e1 WHERE e1.item = l.item))"
    return f"""{base(name)}, {hashes('hp', p.hashes())}, {phase(p)}, {SCORES}, {boundary('scores', p.theta)},
    ph1 AS (SELECT rid, key FROM ph WHERE phase = 1), ph2 AS (SELECT rid, key, g {heavy} (SELECT p FROM bd) AS heavy FROM ph JOIN scores USING (item) WHERE phase = 2),
    {one_hot('ph2', p, 'st', 'heavy')}, {sums(p)}{first},
    est AS (SELECT l.item, CASE WHEN g {heavy} (SELECT p FROM bd) THEN g ELSE {light} END AS f_hat, CASE WHEN g {heavy} (SELECT p FROM bd) THEN 'heavy' ELSE 'light' END AS path FROM (SELECT item, s1, n FROM st_s, st_n) l JOIN scores USING (item))"""


def q(ctes: str, select: str) -> str:
    return f"WITH {ctes} {select}"


BOTH = "SELECT item, f_hat FROM est"


def errors_of(kinds: dict[str, str]) -> str:
    return " UNION ALL ".join(f"SELECT '{m}' AS method, item, f_hat FROM ({q(sql, BOTH)})" for m, sql in kinds.items())


METHODS = {"onehot": one_hot_estimate("types", SMALL), "hadamard": hadamard_estimate("types", SMALL), "pooled_lh": local_hash_estimate("types", SMALL), "split": split("types", SMALL)}
ERR = f"e AS ({errors_of(METHODS)}), t AS (SELECT event_type AS item, count(*)::BIGINT AS f FROM events GROUP BY 1), err AS (SELECT method, item, f, f_hat, (f_hat - f) * (f_hat - f) AS e2 FROM e JOIN t USING (item))"
VERSIONS = "v(version, valid_from, valid_to) AS (SELECT 'v' || i, t0 + to_days(i * 7), t0 + to_days(i * 7 + 7) FROM (SELECT date_trunc('day', min(ts)) AS t0 FROM events), generate_series(0, 3) s(i))"


def event_signs(p: Params) -> str:
    had = hadamard("types", p)
    sign = f"CASE WHEN {coin('rid', p, 'flip')} < {threshold(p.hadamard_q)} THEN -1 ELSE 1 END * (1 - 2 * (bit_count(l & {place('key', p.m)}) % 2))"
    return f"{had}, sg AS (SELECT ts, dr.j, l, {sign} AS sign FROM dr JOIN hp ON hp.j = dr.j JOIN events e ON e.event_id::VARCHAR = dr.rid)"


def theory(kind: str, p: Params) -> str:
    m, k, c = p.m, p.k, p.c
    fac = (m / (m - 1)) ** 2
    noise = (c * c - 1) / 4
    if kind == "onehot":
        v = f"{num(fac)} * (n * {num(noise)} + (n - f) / {m} * {num(1 - 1 / m - 1 / k + 1 / (k * m))} + {num(1 / (k * m) - 1 / (k * m * m))} * (f2 - f * f))"
    elif kind == "hadamard":
        v = f"{num(fac)} * (n * {num(p.hadamard_c ** 2)} + f2 / {k * m})"
    else:
        g = 1 / p.g
        v = f"n * {num(g * (1 - g) / (p.keep - g) ** 2)} + f2 * {num(g * (1 - g) / p.k_pool)}"
    return f"SELECT '{kind}' AS method, round(avg({v}), 3) AS variance FROM truth, (SELECT sum(f)::BIGINT AS n, sum(f * f)::BIGINT AS f2 FROM truth)"


def oracles() -> dict[str, str]:
    p, w, cm = SMALL, WORDS, COUNT
    half, gexp = w.but(flip="half"), w.but(g_rule="exp")
    out = {f"exact_{n}": q(base(n), "SELECT item, f FROM truth") for n in ("words", "parts", "customers", "sensor_fine", "sensor_coarse", "types", "props", "users", "chat_words", "hosts")}
    out |= {
        "domain_stats": " UNION ALL ".join(f"SELECT '{n}' AS fixture, * FROM ({q(base(n), 'SELECT sum(f)::BIGINT AS n, count(*)::BIGINT AS d, max(f)::BIGINT AS f_max FROM truth')})" for n in ("words", "parts", "sensor_fine", "types")),
        "phase_split": q(f"{base('parts')}, {phase(p)}", "SELECT phase, count(*)::BIGINT AS n, sum(key)::BIGINT AS key_sum FROM ph GROUP BY phase"),
        "domain_sample": q(base("words"), "SELECT item, key FROM d ORDER BY md5(item || '|7|domain'), item LIMIT 1000"),
        "encode_example": "WITH l AS (SELECT ((l_linenumber - 1) % 6)::INTEGER AS place, count(*)::BIGINT AS n FROM lineitem GROUP BY 1), k AS (SELECT 'light' AS kind, place, n FROM l UNION ALL SELECT 'dummy', -1, coalesce(sum(n), 0)::BIGINT FROM l) SELECT kind, place, b::INTEGER AS b, CASE WHEN b = place THEN 1 ELSE -1 END::INTEGER AS bit, n FROM k, generate_series(0, 5) t(b)",
        "onehot_state": q(f"{base('parts')}, {hashes('hp', p.hashes())}, {one_hot('c', p)}", "SELECT j::INTEGER AS j, b::INTEGER AS b, plus, reports FROM st"),
        "onehot_cells": q(f"{base('types')}, {hashes('hp', p.hashes())}, {one_hot('c', p)}", f"SELECT j::INTEGER AS j, b::INTEGER AS b, {num(p.k / 2)} * ({num(p.c)} * (2 * plus - reports) + reports) AS cell FROM st"),
        "state_as_array": q(f"{base('types')}, {hashes('hp', p.hashes())}, {one_hot('c', p)}", "SELECT j::INTEGER AS j, string_agg(plus::VARCHAR, ',' ORDER BY b) AS plus FROM st GROUP BY j"),
        "merge_states": q(f"{base('types')}, {hashes('hp', p.hashes())}, {one_hot('c', p)}", "SELECT j::INTEGER AS j, b::INTEGER AS b, plus, reports FROM st"),
        "onehot_estimate": q(one_hot_estimate("parts", p), BOTH),
        "gather_estimate": q(one_hot_estimate("parts", p), BOTH),
        "hadamard_state": q(hadamard("words", w), "SELECT j::INTEGER AS j, l::INTEGER AS l, signed_sum, reports FROM st"),
        "hadamard_estimate": q(hadamard_estimate("words", w), BOTH),
        "hadamard_butterfly_estimate": q(hadamard_estimate("words", w), BOTH),
        "hadamard_half_estimate": q(hadamard_estimate("words", half), BOTH),
        "pooled_lh_state": q(local_hash("words", w), "SELECT j::INTEGER AS j, y::INTEGER AS y, cnt FROM st"),
        "pooled_lh_estimate": q(local_hash_estimate("words", w), BOTH),
        "pooled_lh_gexp_estimate": q(local_hash_estimate("words", gexp), BOTH),
        "pooled_lh_precomputed_estimate": q(local_hash_estimate("parts", p), BOTH),
        "countmin_estimate": q(count_estimate("words", cm, "min"), BOTH),
        "countmin_bound": q(count_estimate("words", cm, "min"), f"SELECT count(*)::BIGINT AS n_items, sum(CASE WHEN f_hat - f > {num(math.e / cm.m)} * n THEN 1 ELSE 0 END)::BIGINT AS violations, sum(CASE WHEN f_hat < f THEN 1 ELSE 0 END)::BIGINT AS underestimates FROM est JOIN truth USING (item), (SELECT sum(f)::BIGINT AS n FROM truth)"),
        "countsketch_mean_estimate": q(count_estimate("words", cm, "mean"), BOTH),
        "countsketch_median_estimate": q(count_estimate("words", cm, "median"), BOTH),
        "rowmean_estimate": q(count_estimate("words", cm, "row"), BOTH),
        "phase1_targets": q(f"{base('parts')}, {hashes('hp', p.hashes())}, {phase(p)}, ph1 AS (SELECT rid, key FROM ph WHERE phase = 1), {one_hot('ph1', p)}, {sums(p)}", f"SELECT item, {value(p)} / {num(p.r)} AS f_target FROM st_s, st_n"),
        "boundary_table": q(f"{base('words')}, {SCORES}, {boundary('scores', 0.5)}", "SELECT p, prefix_len, total, realised FROM bd"),
        "boundary_scalable": q(f"{base('words')}, {SCORES}, {boundary('scores', 0.5)}", "SELECT p, prefix_len FROM bd"),
        "boundary_known_total": q(f"{base('words')}, {SCORES}, {boundary('scores', 0.3, '(SELECT sum(f) FROM truth)')}", "SELECT p, prefix_len, total, realised FROM bd"),
        "boundary_ties": q(f"{base('customers')}, {SCORES}, {boundary('scores', 0.65)}", "SELECT p, prefix_len, total, realised FROM bd"),
        "boundary_empty": q(f"{base('types')}, {SCORES}, {boundary('scores', 0.1)}", "SELECT isinf(p) AS no_heavy, prefix_len FROM bd"),
        "boundary_gap": q(f"{base('words')}, x AS (SELECT DISTINCT f::DOUBLE AS g FROM truth ORDER BY g DESC LIMIT 20)", "SELECT row_number() OVER (ORDER BY g DESC)::INTEGER AS rank, g, g - lead(g) OVER (ORDER BY g DESC) AS gap, lag(g) OVER (ORDER BY g DESC) - g AS gap_before, g / max(g) OVER () AS ratio, nth_value(g, 2) OVER (ORDER BY g DESC ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM x"),
        "theta_realised": q(f"{base('parts')}, {SCORES}, {boundary('scores', 0.5)}", "SELECT realised FROM bd"),
        "split_state": q(split("parts", p), "SELECT j::INTEGER AS j, b::INTEGER AS b, plus, reports FROM st"),
        "split_estimate_sketch": q(split("parts", p), "SELECT item, f_hat, path FROM est"),
        "split_estimate_nominal": q(split("parts", p, "nominal", "raw"), "SELECT item, f_hat, path FROM est"),
        "split_estimate_realised": q(split("parts", p, "realised"), "SELECT item, f_hat, path FROM est"),
        "split_estimate_raw": q(split("parts", p, "sketch", "raw"), "SELECT item, f_hat, path FROM est"),
        "split_estimate_pooled": q(split("types", p, "sketch", "pooled"), "SELECT item, f_hat, path FROM est"),
        "split_strict_estimate": q(split("parts", p, "sketch", "population", ">"), "SELECT item, f_hat, path FROM est"),
        "split_silent": q(f"{split('parts', p)}", "SELECT sum(CASE WHEN heavy THEN 1 ELSE 0 END)::BIGINT AS withheld, sum(CASE WHEN heavy THEN 0 ELSE 1 END)::BIGINT AS sent FROM ph2"),
        "heavy_hitters": q(hadamard_estimate("words", w), "SELECT item, f_hat FROM est ORDER BY f_hat DESC, item LIMIT 50"),
        "method_errors": q(ERR, "SELECT method, round(avg(e2), 3) AS mse, round(sum(e2), 2) AS sse, count(*)::BIGINT AS n_items FROM err GROUP BY method UNION ALL SELECT 'all_zero', round(avg(f * f), 3), round(sum(f * f), 2), count(*)::BIGINT FROM t"),
        "error_rollup": q(ERR, "SELECT method, item, round(sum(e2), 2) AS sse, count(*)::BIGINT AS n_items FROM err GROUP BY ROLLUP (method, item)"),
        "error_cube": q(ERR, "SELECT method, item, round(sum(e2), 2) AS sse, count(*)::BIGINT AS n_items FROM err GROUP BY CUBE (method, item)"),
        "pivot_methods": q(ERR, "SELECT item, " + ", ".join(f"round(max(CASE WHEN method = '{m}' THEN e2 END), 2) AS {m}" for m in METHODS) + " FROM err GROUP BY item"),
        "unpivot_errors": q(ERR, "SELECT item, method, round(e2, 2) AS mse FROM err"),
        "error_quantiles": q(f"{hadamard_estimate('words', w)}, err AS (SELECT (f_hat - f) * (f_hat - f) AS e2 FROM est JOIN truth USING (item))", "SELECT round(quantile_cont(e2, 0.5), 2) AS q50, round(quantile_cont(e2, 0.9), 2) AS q90, round(quantile_cont(e2, 0.99), 2) AS q99 FROM err"),
        "sse_curve": q(f"{count_estimate('words', cm, 'min')}, err AS (SELECT f, count(*) AS n, sum((f_hat - f) * (f_hat - f)) AS s FROM est JOIN truth USING (item) GROUP BY f)", "SELECT f, sum(n) OVER (ORDER BY f DESC ROWS UNBOUNDED PRECEDING)::BIGINT AS n_items, sum(s) OVER (ORDER BY f DESC ROWS UNBOUNDED PRECEDING)::DOUBLE AS sse FROM err"),
        "sse_by_path": q(split("parts", p), "SELECT path, round(sum((f_hat - f) * (f_hat - f)), 2) AS sse, round(avg((f_hat - f) * (f_hat - f)), 3) AS mse, count(*)::BIGINT AS n_items FROM est JOIN truth USING (item) GROUP BY path"),
        "theory_variance": q(base("words"), " UNION ALL ".join(theory(kind, w) for kind in ("onehot", "hadamard", "pooled_lh"))),
        "crossover": q(f"{base('words')}, {SCORES}, {boundary('scores', 0.5)}", f"SELECT hf2 / {w.k * w.m} AS gain, n * {num(w.r / (1 - w.r) * (w.c ** 2 - 1) / 4)} AS cost, hf2 / {w.k * w.m} > n * {num(w.r / (1 - w.r) * (w.c ** 2 - 1) / 4)} AS split_wins FROM (SELECT sum(CASE WHEN f >= (SELECT p FROM bd) THEN f * f ELSE 0 END)::BIGINT AS hf2, sum(f)::BIGINT AS n FROM truth)"),
        "privacy_ratio": q(
            f"i(name, code) AS (SELECT DISTINCT 'place ' || ((l_linenumber - 1) % 6), 1::BIGINT << ((l_linenumber - 1) % 6) FROM lineitem UNION ALL SELECT 'dummy', 0), o AS (SELECT name, o, pow({num(p.q)}, bit_count(xor(o::BIGINT, code::BIGINT))) * pow({num(1 - p.q)}, 6 - bit_count(xor(o::BIGINT, code::BIGINT))) AS pr FROM i, generate_series(0, 63) t(o))",
            f"SELECT a.name || '-' || b.name AS pair, round(max(greatest(a.pr / b.pr, b.pr / a.pr)), 6) AS max_ratio, round(CASE WHEN a.name = 'dummy' THEN {num(math.exp(p.eps / 2))} ELSE {num(math.exp(p.eps))} END, 6) AS bound FROM o a JOIN o b ON a.o = b.o AND a.name < b.name GROUP BY a.name, b.name",
        ),
        "space_table": q(base("parts"), "SELECT method, sketch_bytes, report_bytes, report_bytes * n AS all_report_bytes FROM (SELECT coalesce(sum(f), 0)::BIGINT AS n, count(*)::BIGINT AS d FROM truth), LATERAL (SELECT * FROM (VALUES ('split', 524288::BIGINT, 129::BIGINT), ('onehot', 524288, 129), ('hadamard', 524288, 3), ('pooled_lh', 57344, 2), ('exact', 16 * d, 8)) t(method, sketch_bytes, report_bytes))"),
        "laplace_counts": q(f"{base('types')}, u AS (SELECT item, f, ({coin('item', p, 'laplace')} + 0.5e0) / 268435456e0 - 0.5e0 AS u FROM truth)", f"SELECT item, round(f - sign(u) * ln(1 - 2 * abs(u)) / {num(p.eps)}, 6) AS f_hat FROM u"),
        "bound_contribution": "SELECT user_id, min(event_id)::BIGINT AS event_id FROM events GROUP BY user_id",
        "daily_sketch": q(event_signs(p), "SELECT substr(date_trunc('day', ts)::VARCHAR, 1, 10) AS day, j::INTEGER AS j, l::INTEGER AS l, sum(sign)::BIGINT AS signed_sum, count(*)::BIGINT AS reports FROM sg GROUP BY ALL"),
        "sliding_sketch": q(event_signs(p), "SELECT substr((date_trunc('day', ts) - to_days(i))::VARCHAR, 1, 10) AS day, j::INTEGER AS j, l::INTEGER AS l, sum(sign)::BIGINT AS signed_sum, count(*)::BIGINT AS reports FROM sg, generate_series(0, 6) t(i) GROUP BY ALL"),
        "attach_version": q(VERSIONS, "SELECT event_id, version FROM events JOIN v ON ts >= valid_from AND ts < valid_to"),
        "asof_version": q(VERSIONS, "SELECT event_id, version FROM events ASOF LEFT JOIN v ON ts >= valid_from"),
        "range_join": "SELECT band, count(*)::BIGINT AS n FROM events JOIN (SELECT 'b' || i AS band, i * 7.5e0 AS lo, (i + 1) * 7.5e0 AS hi FROM generate_series(0, 40) t(i)) r ON value >= lo AND value < hi GROUP BY band",
        "rank_items": q(f"{base('words')}, x AS (SELECT item, f FROM truth ORDER BY f DESC, item LIMIT 100)", "SELECT item, f, rank() OVER (ORDER BY f DESC)::INTEGER AS rank, dense_rank() OVER (ORDER BY f DESC)::INTEGER AS dense_rank, row_number() OVER (ORDER BY f DESC, item)::INTEGER AS row_number, ntile(4) OVER (ORDER BY f DESC, item)::INTEGER AS quarter, round(percent_rank() OVER (ORDER BY f DESC), 6) AS percent_rank, round(cume_dist() OVER (ORDER BY f DESC), 6) AS cume_dist FROM x"),
        "top_by_group": "SELECT grp, item, f, rn FROM (SELECT *, row_number() OVER (PARTITION BY grp ORDER BY f DESC, item)::INTEGER AS rn FROM (SELECT event_type AS grp, user_id AS item, count(*)::BIGINT AS f FROM events GROUP BY ALL)) WHERE rn <= 3",
        "moving_count": "SELECT item, day, f, sum(f) OVER (PARTITION BY item ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW)::BIGINT AS moving FROM (SELECT event_type AS item, date_diff('day', DATE '1970-01-01', ts::DATE)::INTEGER AS day, count(*)::BIGINT AS f FROM events GROUP BY ALL)",
        "unseen_items": q(f"{base('words')}, {phase(p)}", "SELECT DISTINCT item FROM ph WHERE phase = 2 AND item NOT IN (SELECT item FROM ph WHERE phase = 1)"),
        "restrict_candidates": q(f"t AS MATERIALIZED (SELECT item, count(*)::BIGINT AS f FROM ({CLIENTS['words']}) GROUP BY item), top AS MATERIALIZED (SELECT item FROM t ORDER BY f DESC, item LIMIT 20)", "SELECT item, f FROM t JOIN top USING (item)"),
        "domain_diff": f"WITH a AS (SELECT DISTINCT item FROM ({CLIENTS['words']})), b AS (SELECT DISTINCT item FROM ({CLIENTS['chat_words']})) SELECT 'left' AS side, count(*)::BIGINT AS n FROM a WHERE item NOT IN (SELECT item FROM b) UNION ALL SELECT 'right', count(*)::BIGINT FROM b WHERE item NOT IN (SELECT item FROM a) UNION ALL SELECT 'both', count(*)::BIGINT FROM a WHERE item IN (SELECT item FROM b)",
        "diff_estimates": f"WITH a AS (SELECT DISTINCT item FROM ({CLIENTS['words']})), b AS (SELECT DISTINCT item FROM ({CLIENTS['chat_words']})) SELECT side, count(*)::BIGINT AS n FROM (SELECT CASE WHEN a.item IS NULL THEN 'right' ELSE 'left' END AS side FROM a FULL JOIN b ON a.item = b.item WHERE a.item IS NULL OR b.item IS NULL) GROUP BY side",
        "filter_labels": q("c AS (SELECT * FROM (" + CLIENTS["words"] + ") WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1))", "SELECT count(*)::BIGINT AS n, count(DISTINCT item)::BIGINT AS d FROM c"),
        "postprocess_clip": q(hadamard_estimate("types", p), "SELECT item, greatest(f_hat, 0) AS f_hat FROM est"),
        "score_join": q(f"{base('parts')}, {SCORES}", "SELECT count(*)::BIGINT AS n, sum(CASE WHEN g >= 30 THEN g ELSE 0 END) AS g_sum FROM c LEFT JOIN (SELECT * FROM scores WHERE g >= 30) USING (item)"),
    }
    pb = p
    for kind, (keep, set_) in {"symmetric": (1 - pb.q, pb.q), "asymmetric": (0.5, 1 / (2.718281828459045**pb.eps + 1))}.items():
        u = f"('0x' || substr(md5(c.rid || '|{pb.seed}|{kind}|' || d.item), 1, 7))::BIGINT"
        out[f"bitvector_{kind}_estimate"] = q(f"{base('types')}, s AS (SELECT d.item, sum(CASE WHEN {u} < CASE WHEN c.item = d.item THEN {threshold(keep)} ELSE {threshold(set_)} END THEN 1 ELSE 0 END)::BIGINT AS s, count(*)::BIGINT AS n FROM c CROSS JOIN d GROUP BY d.item)", f"SELECT item, (s - n * {num(set_)}) / {num(keep - set_)} + 0 AS f_hat FROM s")
    own = f"h AS (SELECT rid, key, 1 + ('0x' || substr(md5(rid || '|{p.seed}|a|0'), 1, 15))::BIGINT % 2147483646 AS a, ('0x' || substr(md5(rid || '|{p.seed}|b|0'), 1, 15))::BIGINT % {P31} AS b FROM c)"
    hh = f"((a * key + b) % {P31} % {p.g})"
    out["own_hash_estimate"] = q(f"{base('types')}, {own}, r AS (SELECT a, b, CASE WHEN {coin('rid', p, 'keep')} < {threshold(p.keep)} THEN {hh} ELSE ({hh} + 1 + {uniform('rid', p, 'other', p.g - 1)}) % {p.g} END AS y FROM h), s AS (SELECT d.item, sum(CASE WHEN (r.a * d.key + r.b) % {P31} % {p.g} = r.y THEN 1 ELSE 0 END)::BIGINT AS s, count(*)::BIGINT AS n FROM r CROSS JOIN d GROUP BY d.item)", f"SELECT item, (s - n / {p.g}) / {num(p.keep - 1 / p.g)} + 0 AS f_hat FROM s")
    flip = 1 / (2.718281828459045 ** (p.eps / 4) + 1)
    out["bloom_bits_estimate"] = q(
        f"{base('types')}, {hashes('hp', p.hashes(2))}, pl AS (SELECT c.rid, list({place('key', p.m)}) AS places FROM c CROSS JOIN hp GROUP BY c.rid), bits AS (SELECT t.b, sum(CASE WHEN list_contains(places, t.b) <> (('0x' || substr(md5(rid || '|{p.seed}|bloom|' || t.b), 1, 7))::BIGINT < {threshold(flip)}) THEN 1 ELSE 0 END)::BIGINT AS s, count(*)::BIGINT AS n FROM pl, generate_series(0, {p.m - 1}) t(b) GROUP BY t.b)",
        f"SELECT d.item, min((s - n * {num(flip)}) / {num(1 - 2 * flip)}) + 0 AS f_hat FROM d CROSS JOIN hp JOIN bits ON bits.b = {place('d.key', p.m)} GROUP BY d.item",
    )
    seg = f"SELECT o_orderkey::VARCHAR AS rid, c_mktsegment AS segment, o_orderpriority AS item, {str_key('o_orderpriority')} AS key FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
    out["segment_report"] = q(
        f"c AS ({seg}), d AS (SELECT DISTINCT segment, item, key FROM c), {hashes('hp', p.hashes(p.k_pool))}, dr AS (SELECT rid, segment, key, {uniform('rid', p, 'row', p.k_pool)} AS j FROM c), rp AS (SELECT segment, dr.j, CASE WHEN {coin('rid', p, 'keep')} < {threshold(p.keep)} THEN {place('key', p.g)} ELSE ({place('key', p.g)} + 1 + {uniform('rid', p, 'other', p.g - 1)}) % {p.g} END AS y FROM dr JOIN hp ON hp.j = dr.j), st AS (SELECT segment, j, y, count(*)::BIGINT AS cnt FROM rp GROUP BY ALL), n AS (SELECT segment, sum(cnt)::BIGINT AS n FROM st GROUP BY segment), s AS (SELECT d.segment, d.item, coalesce(sum(st.cnt), 0)::BIGINT AS s FROM d CROSS JOIN hp LEFT JOIN st ON st.segment = d.segment AND st.j = hp.j AND st.y = {place('d.key', p.g)} GROUP BY ALL)",
        f"SELECT segment, item, (s - n / {p.g}) / {num(p.keep - 1 / p.g)} + 0 AS f_hat FROM s JOIN n USING (segment)",
    )
    point = lambda p: {"onehot": one_hot_estimate("types", p), "hadamard": hadamard_estimate("types", p), "pooled_lh": local_hash_estimate("types", p), "split": split("types", p)}
    for name, values in GRIDS.items():
        parts = [f"SELECT {num(v)} AS value, '{m}' AS method, round(avg((f_hat - f) * (f_hat - f)), 3) AS mse, count(*)::BIGINT AS n_items FROM ({q(ctes, 'SELECT item, f_hat, f FROM est JOIN truth USING (item)')})" for v in values for m, ctes in point(p.but(**{name: v})).items()]
        out[f"grid_{name}"] = " UNION ALL ".join(parts)
    out["error_grouping_sets"] = q(ERR, "SELECT method, item, round(sum(e2), 2) AS sse, count(*)::BIGINT AS n_items FROM err GROUP BY GROUPING SETS ((method), (item))")
    out["postprocess_shift"] = q(base("types"), "SELECT round(sum(f)::DOUBLE, 3) AS total, 0::BIGINT AS negative, count(*)::BIGINT AS n_items FROM truth")
    out["postprocess_significant"] = q(hadamard_estimate("types", p), "SELECT item, CASE WHEN f_hat >= 1000 THEN f_hat ELSE 0 END AS f_hat FROM est")
    fac, noise, size = num((w.m / (w.m - 1)) ** 2), (w.c**2 - 1) / 4, w.k * w.m
    light, heavy = f"{fac} * (n * {num(noise / (1 - w.r))} + lf2 / {size})", f"{fac} * (n * {num(noise / w.r)} + f2 / {size})"
    out["theory_split"] = q(
        f"{base('words')}, {SCORES}, {boundary('scores', w.theta)}, m AS (SELECT sum(f)::BIGINT AS n, sum(f * f)::BIGINT AS f2, sum(CASE WHEN f < (SELECT p FROM bd) THEN f * f ELSE 0 END)::BIGINT AS lf2, sum(CASE WHEN f >= (SELECT p FROM bd) THEN 1 ELSE 0 END)::BIGINT AS nh, sum(CASE WHEN f >= (SELECT p FROM bd) THEN f ELSE 0 END)::BIGINT AS hn, count(*)::BIGINT AS d FROM truth)",
        f"SELECT round({light}, 3) AS light, round({heavy}, 3) AS heavy, round(({light} * (d - nh) + {heavy} * nh) / d, 3) AS total, round({fac} * (n * {num(noise)} + (n * {num(1 - w.theta)} - (n - hn) / (d - nh)) / {w.m} + lf2 / {size}), 3) AS bound FROM m",
    )
    a = AUDIT
    out["privacy_audit"] = q(
        f"{base('types')}, {hashes('hp', a.hashes())}, x AS (SELECT rid, key % 2 = 1 AS heavy, CASE WHEN key % 2 = 1 THEN -1 ELSE {place('key', a.m)} END AS pos FROM c, hp), bits AS (SELECT rid, heavy, t.b, (t.b = pos) <> (('0x' || substr(md5(rid || '|{a.seed}|bit|0'), 1 + 7 * t.b, 7))::BIGINT < {threshold(a.q)}) AS plus FROM x, (VALUES (0), (1), (2)) t(b)), o AS (SELECT rid, heavy, sum(CASE WHEN plus THEN 1 << t.b ELSE 0 END) AS out FROM bits t GROUP BY rid, heavy), n AS (SELECT heavy, out, count(*) AS n FROM o GROUP BY ALL), sh AS (SELECT heavy, out, n / sum(n) OVER (PARTITION BY heavy) AS share FROM n), ra AS (SELECT out, max(share) / min(share) AS ratio FROM sh GROUP BY out HAVING count(*) = 2)",
        f"SELECT 'heavy-light' AS paths, round(max(ratio), 6) AS max_ratio, round({num(math.exp(a.eps / 2))}, 6) AS bound FROM ra",
    )
    pairs = " UNION ALL ".join(f"SELECT {m}::INTEGER AS m, {k}::INTEGER AS k, '{pair}' AS pair, round({v}, 9) AS covariance, {count} AS pairs FROM s" for m, k in ((8, 2), (64, 8), (1024, 64)) for pair, v, count in (("same_other", f"1e0 / {m} - 1e0 / {m * m}", "f2 - n"), ("different", "0e0", "n * n - f2"), ("dummy", "0e0", "2 * n * h")))
    out["theory_covariance"] = q(f"{base('parts')}, s AS (SELECT sum(f) FILTER (item % 2 = 0)::BIGINT AS n, sum(f * f) FILTER (item % 2 = 0)::BIGINT AS f2, sum(f) FILTER (item % 2 = 1)::BIGINT AS h FROM truth)", pairs)
    u = f"({coin(LINE, p, 'zipf')} / {num(COIN)})"
    out["zipf_stats"] = q(f"c AS (SELECT floor(pow(1 - {u} * {num(1 - 2_000_000 ** (1 - 1.1))}, {num(-1 / (1.1 - 1))}))::BIGINT AS item FROM lineitem), truth AS (SELECT item, count(*)::BIGINT AS f FROM c GROUP BY item)", "SELECT sum(f)::BIGINT AS n, count(*)::BIGINT AS d, max(f)::BIGINT AS f_max FROM truth")
    two = f"{base('types')}, {hashes('hp', p.hashes())}, {phase(p)}, ph1 AS (SELECT rid, key FROM ph WHERE phase = 1), ph2 AS (SELECT rid, key FROM ph WHERE phase = 2), {one_hot('ph1', p, 'a')}, {sums(p, 'a')}, {one_hot('ph2', p, 'b2')}, {sums(p, 'b2')}"
    out["two_round_heavy_hitters"] = q(f"{two}, top AS (SELECT item, {value(p)} AS f1 FROM a_s, a_n ORDER BY f1 DESC, item LIMIT 3)", f"SELECT item, {value(p)} / {num(1 - p.r)} AS f_hat FROM b2_s, b2_n WHERE item IN (SELECT item FROM top)")
    return out
