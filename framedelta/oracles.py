"""DuckDB SQL of the encoder, built for a shape: what the queries of workloads.py are held against. It shares no code with the kernel.

Weights of the backbone are made in SQL from their integer formula; those of gates and calibrators are literals. Tokens are rows with list columns.
"""

from __future__ import annotations

import numpy as np

from .model import EncoderSpec, ReuseConfig


def _formula(layer: int, part: int, rows: int, seed: int, i: str = "i", j: str = "j") -> str:
    n = f"((7919 * {i} + 104729 * {j} + {1299709 * layer + 15485863 * part + 6700417 * seed} + (31 * {i} + 17 * {j}) * (31 * {i} + 17 * {j})) % 2003)"
    return f"(CAST({n} AS DOUBLE) / 2003 - CAST(0.5 AS DOUBLE)) * sqrt(CAST(12 AS DOUBLE) / {rows})"


def _columns(layer: int, part: int, rows: int, cols: int, seed: int) -> str:
    """A weight matrix as the list of its columns."""
    return f"list_transform(range(0, {cols}), lambda j: list_transform(range(0, {rows}), lambda i: {_formula(layer, part, rows, seed)}))"


def _times(vec: str, columns: str) -> str:
    return f"list_transform({columns}, lambda c: list_dot_product(c, {vec}))"


def _plus(a: str, b: str, n: int) -> str:
    return f"list_transform(range(1, {n + 1}), lambda i: {a}[i] + {b}[i])"


def _normed(source: str, column: str, out: str) -> str:
    """source's rows and the normalised column."""
    mean = f"(SELECT *, list_avg({column}) AS m_ FROM {source})"
    spread = f"(SELECT *, sqrt(list_avg(list_transform({column}, lambda a: (a - m_) * (a - m_))) + 1e-6) AS s_ FROM {mean})"
    return f"SELECT * EXCLUDE (m_, s_), list_transform({column}, lambda a: (a - m_) / s_) AS {out} FROM {spread}"


GELU = "list_transform({0}, lambda a: CAST(0.5 AS DOUBLE) * a * (1 + tanh(CAST(0.7978845608028654 AS DOUBLE) * (a + CAST(0.044715 AS DOUBLE) * a * a * a))))"


def _literal(m: np.ndarray) -> str:
    """A matrix as the list of its columns, or a vector as a list."""
    row = lambda v: "[" + ", ".join(f"{x:.17g}::DOUBLE" for x in v) + "]"
    return row(m) if m.ndim == 1 else "[" + ", ".join(row(c) for c in m.T) + "]"


def _start(spec: EncoderSpec) -> list[str]:
    """Weights (one row) and embedded tokens x0 (v, f, t, raw, x) of tok (v, f, t, raw)."""
    d, n, m = spec.dim, spec.n_tokens, spec.ffn_mult * spec.dim
    cols = [f"{_columns(0, 0, spec.in_dim, d, spec.seed)} AS w_embed", f"list_transform(range(0, {n}), lambda i: list_transform(range(0, {d}), lambda j: {_formula(0, 1, n, spec.seed)} * CAST(0.5 AS DOUBLE) * sqrt(CAST({n} AS DOUBLE)))) AS w_pos"]
    for k in range(spec.layers):
        cols += [f"{_columns(k, 2, d, 3 * d, spec.seed)} AS w_qkv{k}", f"{_columns(k, 3, d, d, spec.seed)} AS w_out{k}", f"{_columns(k, 4, d, m, spec.seed)} AS w_up{k}", f"{_columns(k, 5, m, d, spec.seed)} AS w_down{k}"]
    return [
        f"w AS MATERIALIZED (SELECT {', '.join(cols)})",
        f"x0 AS MATERIALIZED (SELECT v, f, t, {_plus('e_', 'w_pos[t + 1]', d)} AS x FROM (SELECT v, f, t, {_times('raw', 'w_embed')} AS e_ FROM tok, w), w)",
        f"n0 AS MATERIALIZED ({_normed('x0', 'x', 'n_')})",
        f"q0 AS MATERIALIZED (SELECT v, f, t, x, {_times('n_', 'w_qkv0')} AS q FROM n0, w)",
    ]


def _attended(spec: EncoderSpec, k: int, prune: int = 0) -> list[str]:
    """h{k} (v, f, t, h, imp, branch, q): unit inputs after attention over q{k}, with the class token's attention and the fresh unit outputs.

    With prune the tokens of least attention from the class token leave after the attention of each layer.
    """
    d, dh = spec.dim, spec.dim // spec.heads
    heads = []
    for head in range(spec.heads):
        a = head * dh
        heads.append(f"list_transform(kv, lambda o: list_dot_product(q[{a + 1}:{a + dh}], o[{d + a + 1}:{d + a + dh}]) / sqrt(CAST({dh} AS DOUBLE))) AS s{head}")
    soft = [f"list_transform(s{i}, lambda z: exp(z - list_max(s{i}))) AS p{i}" for i in range(spec.heads)]
    share = [f"list_transform(p{i}, lambda z: z / list_sum(p{i})) AS a{i}" for i in range(spec.heads)]
    mixed = " || ".join(f"list_transform(range({2 * d + i * dh + 1}, {2 * d + (i + 1) * dh + 1}), lambda j: list_dot_product(a{i}, list_transform(kv, lambda o: o[j])))" for i in range(spec.heads))
    mean = f"list_transform(range(1, {spec.n_tokens - k * prune + 1}), lambda j: ({' + '.join(f'a{i}[j]' for i in range(spec.heads))}) / {spec.heads})"
    rated = f"SELECT v, f, t, h, cls[t + 1] AS imp FROM g{k} JOIN c{k} USING (v, f)"
    if prune:
        at = f"SELECT v, f, t, h, cls[row_number() OVER (PARTITION BY v, f ORDER BY t)] AS imp FROM g{k} JOIN c{k} USING (v, f)"
        rated = f"SELECT * FROM ({at}) QUALIFY row_number() OVER (PARTITION BY v, f ORDER BY t = 0 DESC, imp DESC, t) <= {spec.n_tokens - (k + 1) * prune}"
    out = [
        f"kv{k} AS MATERIALIZED (SELECT v, f, list(q ORDER BY t) AS kv FROM q{k} GROUP BY v, f)",
        f"a{k} AS MATERIALIZED (SELECT v, f, t, x, {mixed} AS mixed, {mean} AS imp FROM (SELECT *, {', '.join(share)} FROM (SELECT *, {', '.join(soft)} FROM (SELECT q{k}.*, kv, {', '.join(heads)} FROM q{k} JOIN kv{k} USING (v, f)))))",
        f"g{k} AS MATERIALIZED (SELECT v, f, t, {_plus('x', 'o_', d)} AS h, imp FROM (SELECT *, {_times('mixed', f'w_out{k}')} AS o_ FROM a{k}, w))",
        f"c{k} AS (SELECT v, f, imp AS cls FROM g{k} WHERE t = 0)",
        f"gn{k} AS MATERIALIZED ({_normed(f'({rated})', 'h', 'n_')})",
        f"u{k} AS MATERIALIZED (SELECT v, f, t, h, imp, {_times('up_', f'w_down{k}')} AS branch FROM (SELECT *, {GELU.format('up0_')} AS up_ FROM (SELECT *, {_times('n_', f'w_up{k}')} AS up0_ FROM gn{k}, w)))",
    ]
    if k + 1 < spec.layers:
        out += [
            f"un{k} AS MATERIALIZED ({_normed(f'(SELECT *, {_plus("h", "branch", d)} AS y_ FROM u{k})', 'y_', 'n_')})",
            f"h{k} AS MATERIALIZED (SELECT v, f, t, h, imp, branch, {_times('n_', f'w_qkv{k + 1}')} AS q FROM un{k}, w)",
        ]
    else:
        out += [f"h{k} AS (SELECT *, CAST([] AS DOUBLE[]) AS q FROM u{k})"]
    return out


def _end(spec: EncoderSpec) -> list[str]:
    return [f"zn AS (SELECT v, f, x FROM q{spec.layers} WHERE t = 0)", f"z AS MATERIALIZED ({_normed('zn', 'x', 'e')})"]


def exact_ctes(spec: EncoderSpec, prune: int = 0) -> str:
    """z (v, f, e): embeddings of tok by the unmodified encoder, or with `prune` tokens less after each layer's attention."""
    parts = _start(spec)
    for k in range(spec.layers):
        parts += _attended(spec, k, prune)
        parts.append(f"q{k + 1} AS MATERIALIZED (SELECT v, f, t, {_plus('h', 'branch', spec.dim)} AS x, q FROM h{k})")
    return ",\n".join(parts + _end(spec))


def _cosine(a: str, b: str) -> str:
    size = f"sqrt(list_dot_product({a}, {a})) * sqrt(list_dot_product({b}, {b}))"
    return f"CASE WHEN {size} > 0 THEN list_dot_product({a}, {b}) / ({size}) ELSE 0 END"


def hints_cte(dim: int) -> str:
    """Motion and residual of token lists a against b as SQL expressions."""
    near = [f"list_sum(list_transform(range(1, {dim + 1}), lambda i: abs(a[i] - b[(i - 1 - ({s}) + {dim}) % {dim} + 1])))" for s in (0, 1, -1, 2, -2)]
    return ", ".join(f"{x} AS d{i}" for i, x in enumerate(near))


MOTION = "CASE WHEN d0 <= least(d1, d2, d3, d4) + 1e-9 THEN 0 WHEN least(d1, d2) <= least(d3, d4) + 1e-9 THEN 0.5 ELSE 1 END::DOUBLE"


def gated_ctes(spec: EncoderSpec, cfg: ReuseConfig, modules: list[dict] | None, waves: int) -> str:
    """z (v, f, e) and reused (v, f, n): the gated encode of tok under the plan pl (v, f, ft, past, future, wave); kinds are I, P, B2, B1.

    The fixed gates (mse, budget) take no modules and correct nothing.
    """
    d, n = spec.dim, spec.n_tokens
    parts = _start(spec)
    for side in ("past", "future"):
        parts.append(f"ht_{side} AS MATERIALIZED (SELECT v, f, t, {MOTION} AS motion, d0 / {spec.in_dim} AS residual FROM (SELECT v, f, t, {hints_cte(spec.in_dim)} FROM (SELECT c.v, c.f, c.t, c.raw AS a, r.raw AS b FROM tok c JOIN pl ON pl.v = c.v AND pl.f = c.f JOIN tok r ON r.v = c.v AND r.f = pl.{side} AND r.t = c.t)))")
    for k in range(spec.layers):
        last = k + 1 == spec.layers
        m = modules[k] if cfg.gate == "learned" else None
        parts += _attended(spec, k)
        fresh = f"SELECT h{k}.v, h{k}.f, h{k}.t, ft, h, branch, q, false AS reused FROM h{k} JOIN pl ON pl.v = h{k}.v AND pl.f = h{k}.f WHERE wave = 0"
        parts.append(f"r{k}_0 AS MATERIALIZED ({fresh})")
        for wv in range(1, waves):
            pick = lambda c: f"CASE WHEN ahead THEN u_{c} ELSE p_{c} END"
            side = f"SELECT h{k}.v, h{k}.f, h{k}.t, pl.ft, h{k}.h, h{k}.imp, h{k}.branch, h{k}.q, p.h AS p_h, u.h AS u_h, p.branch AS p_b, u.branch AS u_b, p.q AS p_q, u.q AS u_q, p.ft AS p_ft, u.ft AS u_ft, hp.motion AS p_m, hu.motion AS u_m, hp.residual AS p_r, hu.residual AS u_r FROM h{k} JOIN pl ON pl.v = h{k}.v AND pl.f = h{k}.f AND pl.wave = {wv} LEFT JOIN r{k}_{wv - 1} p ON p.v = h{k}.v AND p.f = pl.past AND p.t = h{k}.t LEFT JOIN r{k}_{wv - 1} u ON u.v = h{k}.v AND u.f = pl.future AND u.t = h{k}.t LEFT JOIN ht_past hp ON hp.v = h{k}.v AND hp.f = h{k}.f AND hp.t = h{k}.t LEFT JOIN ht_future hu ON hu.v = h{k}.v AND hu.f = h{k}.f AND hu.t = h{k}.t"
            sims = f"SELECT *, CASE WHEN p_h IS NULL THEN -1 ELSE {_cosine('h', 'p_h')} END AS sp, CASE WHEN u_h IS NULL THEN -1 ELSE {_cosine('h', 'u_h')} END AS su FROM ({side})"
            ref = f"SELECT v, f, t, ft, h, imp, branch, q, greatest(sp, su) AS s, {pick('h')} AS r_h, {pick('b')} AS r_b, {pick('q')} AS r_q, {pick('ft')} AS r_ft, {pick('m')} AS r_m, {pick('r')} AS r_r FROM (SELECT *, su > sp + 1e-9 AS ahead FROM ({sims}))"
            feats = f"SELECT *, [s, imp, (r_ft = 'I')::DOUBLE, (r_ft = 'P')::DOUBLE, (r_ft = 'B2')::DOUBLE, (r_ft = 'B1')::DOUBLE, r_m, r_r] AS feat, list_transform(range(1, {d + 1}), lambda i: h[i] - r_h[i]) AS delta FROM ({ref})"
            if m is None:
                change = f"SELECT *, list_dot_product(delta, delta) / {d} AS change FROM ({feats})"
                place = "row_number() OVER (PARTITION BY v, f ORDER BY t = 0 DESC, change DESC, t)"
                test = f"change < {cfg.theta}::DOUBLE" if cfg.gate == "mse" else f"{place} > {cfg.budget + 1}"
                decided = f"SELECT *, t > 0 AND {test} AS reused FROM ({change})"
                branch, q = "r_b", "q" if last else "CASE WHEN reused THEN r_q ELSE q END"
            else:
                hidden = f"SELECT *, list_transform(range(1, {len(m['gb1']) + 1}), lambda i: greatest(list_dot_product(feat, {_literal(m['g1'])}[i]) + {_literal(m['gb1'])}[i], 0)) AS gate_, list_transform(range(1, {len(m['cb1']) + 1}), lambda i: greatest(list_dot_product(delta, {_literal(m['c1'])}[i]) + {_literal(m['cb1'])}[i], 0)) AS cal_ FROM ({feats})"
                wide = len(m["cb2"])
                decided = f"SELECT *, t > 0 AND list_dot_product(gate_, {_literal(m['g2'][:, 0])}) + {float(m['gb2'][0]):.17g}::DOUBLE + {cfg.shift}::DOUBLE > 0 AS reused, list_transform(range(1, {wide + 1}), lambda i: list_dot_product(cal_, {_literal(m['c2'])}[i]) + {_literal(m['cb2'])}[i]) AS extra FROM ({hidden})"
                branch = _plus("r_b", "extra", d) if last else "r_b"
                q = "q" if last else f"CASE WHEN reused THEN {_plus('r_q', 'extra', 3 * d)} ELSE q END"
            parts.append(f"r{k}_{wv} AS MATERIALIZED (SELECT * FROM r{k}_{wv - 1} UNION ALL SELECT v, f, t, ft, h, CASE WHEN reused THEN {branch} ELSE branch END, {q}, reused FROM ({decided}))")
        parts.append(f"q{k + 1} AS MATERIALIZED (SELECT v, f, t, {_plus('h', 'branch', d)} AS x, q FROM r{k}_{waves - 1})")
    counts = " UNION ALL ".join(f"SELECT v, f, reused FROM r{k}_{waves - 1} WHERE t > 0" for k in range(spec.layers))
    parts.append(f"reused AS (SELECT v, f, avg(reused::INT) AS rate FROM ({counts}) GROUP BY v, f)")
    return ",\n".join(parts + _end(spec))


def shown(dim: int) -> str:
    """A few numbers that stand for an embedding e, rounded."""
    picks = [1, dim // 2, dim]
    weighted = f"list_sum(list_transform(range(1, {dim + 1}), lambda i: i * e[i]))"
    return ", ".join([*(f"round(e[{i}], 5) + 0 AS e{i}" for i in picks), f"round({weighted}, 5) + 0 AS weighted"])
