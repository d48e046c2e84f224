"""DuckDB statements that replay the queries: preparation, unrolled iterations, measures, relational operators."""

from __future__ import annotations

from .functions.text import stop_words

SCALE = "1e12"


def stop_values() -> str:
    return ", ".join("('" + w.replace("'", "''") + "')" for w in stop_words())


def base(source: str = "SELECT doc_id, text FROM documents", stop: bool = True) -> str:
    """CTEs tok, cnt, per and a (term, doc_id, tf, df, x)."""
    anti = f"ANTI JOIN (VALUES {stop_values()}) s(term) USING (term)" if stop else ""
    return (
        f"src AS ({source}), "
        r"tok AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM src), "
        f"cnt AS MATERIALIZED (SELECT term, doc_id, count(*) AS tf FROM (SELECT * FROM tok {anti}) GROUP BY term, doc_id), "
        "per AS (SELECT term, CAST(sum(tf) AS BIGINT) AS total, count(*) AS df FROM cnt GROUP BY term HAVING sum(tf) >= 2), "
        "a AS MATERIALIZED (SELECT term, doc_id, tf, df, CAST(tf AS DOUBLE) / df AS x FROM cnt JOIN per USING (term))"
    )


def guess(k: int, seed: int = 0, nnz: int | None = None, name: str = "u0") -> str:
    h = lambda s: f"CAST(('0x' || substr(md5({s}), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE"
    key = f"term || '|' || topic || '|' || '{seed}'"
    rows = f"SELECT term AS row, CAST(topic AS INTEGER) AS topic, {h(key)} AS value FROM (SELECT DISTINCT term FROM a), range({k}) r(topic)"
    if nnz is not None:
        place = key.replace("term", "row") + " || '|place'"
        rows = f"SELECT * FROM ({rows}) WHERE value > 0 ORDER BY {h(place)}, row, topic LIMIT {nnz}"
    return f"{name} AS MATERIALIZED ({rows})"


def rank_of(value: str = "value") -> str:
    return f"round_even({value} * {SCALE}, 0)"


def cut(name: str, raw: str, t: int | None = None, scope: str = "matrix", ties: str = "exact", tau: float | None = None) -> str:
    """Truncation of entries (row, topic, value, b)."""
    where = f"WHERE value > 0{'' if tau is None else f' AND value >= {tau!r}'}"
    if t is None:
        return f"{name} AS MATERIALIZED (SELECT * FROM {raw} {where})"
    by = "PARTITION BY topic " if scope == "topic" else ""
    order = f"{rank_of()} DESC" + (", row, topic" if ties == "exact" else "")
    fn = "row_number()" if ties == "exact" else "rank()"
    return f"{name} AS MATERIALIZED (SELECT row, topic, value, b FROM (SELECT *, {fn} OVER ({by}ORDER BY {order}) AS r FROM {raw} {where}) WHERE r <= {t})"


def wide(name: str, f: str, k: int) -> str:
    cols = ", ".join(f"coalesce(sum(value) FILTER (topic = {i}), 0) AS w{i}" for i in range(k))
    return f"{name} AS (SELECT row, {cols} FROM {f} GROUP BY row)"


def half(out: str, f: str, side: str, k: int, t=None, scope="matrix", ties="exact", tau=None, shift: float = 0.0, extra: str | None = None) -> str:
    """One half step from factor ``f``: side 'v' solves documents, 'u' terms. extra: SELECT of more (row, topic, v) to add."""
    own, to = ("term", "doc_id") if side == "v" else ("doc_id", "term")
    more = f" UNION ALL {extra}" if extra else ""
    parts = [
        wide(f"{out}_w", f, k),
        f"{out}_g AS (SELECT " + ", ".join(f"coalesce(sum(w{i} * w{j}), 0) AS g{i}{j}" for i in range(k) for j in range(i, k)) + f" FROM {out}_w)",
        f"{out}_p AS MATERIALIZED (SELECT row, topic, sum(v) AS b FROM (SELECT a.{to} AS row, f.topic, a.x * f.value AS v FROM a JOIN {f} f ON a.{own} = f.row{more}) GROUP BY ALL)",
        wide(f"{out}_q", f"(SELECT row, topic, b AS value FROM {out}_p)", k),
    ]
    s = [f"(w{i} - {shift!r})" if shift else f"w{i}" for i in range(k)]
    if k == 1:
        solved = [f"{s[0]} / g00"]
    else:
        solved = [f"({s[0]} * g11 - {s[1]} * g01) / (g00 * g11 - g01 * g01)", f"({s[1]} * g00 - {s[0]} * g01) / (g00 * g11 - g01 * g01)"]
    raw = " UNION ALL ".join(f"SELECT row, {i} AS topic, greatest({x}, 0) AS value, w{i} AS b FROM {out}_q, {out}_g" for i, x in enumerate(solved))
    return ", ".join([*parts, f"{out}_r AS MATERIALIZED ({raw})", cut(out, f"{out}_r", t, scope, ties, tau)])


def als(k=2, iters=2, t_u=None, t_v=None, scope="matrix", ties="exact", tau_u=None, tau_v=None, shift=0.0, seed=0, nnz=None, source=None) -> str:
    """CTEs up to u{iters}, v{iters}."""
    out = [base(source) if source else base(), guess(k, seed, nnz)]
    for i in range(1, iters + 1):
        out.append(half(f"v{i}", f"u{i - 1}", "v", k, t_v, scope, ties, tau_v, shift))
        out.append(half(f"u{i}", f"v{i}", "u", k, t_u, scope, ties, tau_u, shift))
    return "WITH " + ", ".join(out)


def entries(f: str) -> str:
    return f" SELECT row, topic, round(value, 6) AS value FROM {f}"


def gram_dot(u: str, v: str) -> str:
    return (
        f"(SELECT sum(x.g * y.g) FROM (SELECT p.topic AS i, q.topic AS j, sum(p.value * q.value) AS g FROM {u} p JOIN {u} q USING (row) GROUP BY ALL) x "
        f"JOIN (SELECT p.topic AS i, q.topic AS j, sum(p.value * q.value) AS g FROM {v} p JOIN {v} q USING (row) GROUP BY ALL) y USING (i, j))"
    )


def change(new: str, old: str) -> str:
    return f"(SELECT sqrt(sum(pow(coalesce(n.value, 0) - coalesce(o.value, 0), 2)) / sum(pow(coalesce(n.value, 0), 2))) FROM {new} n FULL JOIN {old} o USING (row, topic))"


def trace(iters: int) -> str:
    norm = "(SELECT sum(x * x) FROM a)"
    return " " + " UNION ALL ".join(
        f"SELECT {i} AS iter, round({change(f'u{i}', f'u{i - 1}')}, 6) AS residual, "
        f"round(sqrt(greatest(0, {norm} - 2 * (SELECT sum(value * b) FROM u{i}) + {gram_dot(f'u{i}', f'v{i}')}) / {norm}), 6) AS error, "
        f"(SELECT count(*) FROM u{i}) AS nnz_u, (SELECT count(*) FROM v{i}) AS nnz_v"
        for i in range(1, iters + 1)
    )


def sequential(blocks=2, iters=2, t_u=None, t_v=None, seed=0, block=1) -> str:
    """Blocks of ``block`` topics (one or two): CTEs u{b}_{i}, v{b}_{i} of each block, doneu, donev with all topics."""
    out = [base(), guess(block, seed)]
    for b in range(blocks):
        f = "u0"
        for i in range(1, iters + 1):
            v, u = f"v{b}_{i}", f"u{b}_{i}"

            def taken(target: str, own: str, other: str) -> str | None:
                if not b:
                    return None
                c = f"(SELECT p.topic AS t, q.topic AS s, sum(p.value * q.value) AS c FROM done{own}{b} p JOIN {target} q ON p.row = q.row GROUP BY ALL)"
                return f"SELECT d.row, c.s AS topic, -d.value * c.c AS v FROM done{other}{b} d JOIN {c} c ON d.topic = c.t"

            out.append(half(v, f, "v", block, t_v, extra=taken(f, "u", "v")))
            out.append(half(u, v, "u", block, t_u, extra=taken(v, "v", "u")))
            f = u
        for side in "uv":
            earlier = f"SELECT * FROM done{side}{b} UNION ALL " if b else ""
            out.append(f"done{side}{b + 1} AS MATERIALIZED ({earlier}SELECT row, CAST(topic + {b * block} AS INTEGER) AS topic, value FROM {side}{b}_{iters})")
    return "WITH " + ", ".join(out)


def sequential_trace(blocks: int = 2, iters: int = 2) -> str:
    """(iter, residual, error, nnz_u, nnz_v): the residual of each block's own U, the error of all topics so far."""
    norm = "(SELECT sum(x * x) FROM a)"
    rest, rows = norm, []
    for b in range(blocks):
        for i in range(1, iters + 1):
            u, v = f"u{b}_{i}", f"v{b}_{i}"
            left = f"({rest} - 2 * (SELECT sum(value * b) FROM {u}) + {gram_dot(u, v)})"
            rows.append(
                f"SELECT {b * iters + i} AS iter, round({change(u, f'u{b}_{i - 1}' if i > 1 else 'u0')}, 6) AS residual, round(sqrt(greatest(0, {left}) / {norm}), 6) AS error, "
                f"(SELECT count(*) FROM {u}) AS nnz_u, (SELECT count(*) FROM {v}) AS nnz_v"
            )
        rest = left
    return " " + " UNION ALL ".join(rows)


def mean_accuracy(fit: str, v: str, groups: str, j: int, k: int = 2) -> str:
    """The fit's CTEs and acc (topic, n_docs, …, acc), unrounded."""
    return fit + ", acc AS (" + accuracy(v, groups, j, k).replace("round(CASE", "(CASE").replace("END, 6)", "END)") + ")"


def either(*statements: str) -> str:
    """Statements with CTEs of their own, one under the other."""
    return " UNION ALL ".join(f"SELECT * FROM ({s})" for s in statements)


def peak(iters: int) -> str:
    """Most entries of U and V at once, the first guess included."""
    n = lambda f: f"(SELECT count(*) FROM {f}{' WHERE value > 0' if f == 'u0' else ''})"
    held = [n("u0")] + [f"{n(f'u{i - 1}')} + {n(f'v{i}')}" for i in range(1, iters + 1)] + [f"{n(f'u{i}')} + {n(f'v{i}')}" for i in range(1, iters + 1)]
    return f"greatest({', '.join(held)})"


def accuracy(v: str, groups: str, j: int, k: int) -> str:
    """(topic, n_docs, same_pairs, floor_pairs, all_pairs, acc)."""
    return f""" SELECT CAST(t.topic AS INTEGER) AS topic, coalesce(n_docs, 0) AS n_docs, coalesce(same_pairs, 0) AS same_pairs, coalesce(floor_pairs, 0) AS floor_pairs, coalesce(all_pairs, 0) AS all_pairs,
    round(CASE WHEN coalesce(n_docs, 0) < 2 THEN 1.0 ELSE CAST(same_pairs - floor_pairs AS DOUBLE) / (all_pairs - floor_pairs) END, 6) AS acc
FROM range({k}) t(topic) LEFT JOIN (
    SELECT topic, CAST(sum(c) AS BIGINT) AS n_docs, CAST(sum(c * (c - 1) // 2) AS BIGINT) AS same_pairs,
        CAST((sum(c) % {j}) * ((sum(c) // {j} + 1) * (sum(c) // {j}) // 2) + ({j} - sum(c) % {j}) * ((sum(c) // {j}) * (sum(c) // {j} - 1) // 2) AS BIGINT) AS floor_pairs,
        CAST(sum(c) * (sum(c) - 1) // 2 AS BIGINT) AS all_pairs
    FROM (SELECT f.topic, g.grp, count(*) AS c FROM {v} f JOIN ({groups}) g ON f.row = g.doc_id GROUP BY ALL) GROUP BY topic) s USING (topic)"""


def starts(iters: int = 2, k: int = 2) -> tuple[list[str], int, int]:
    """The first CTEs of methods that start both factors from a guess."""
    out = [base(), guess(k)]
    h = "CAST(('0x' || substr(md5(row || '|' || topic || '|v0'), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE"
    out.append(f"v0 AS MATERIALIZED (SELECT row, CAST(topic AS INTEGER) AS topic, {h} AS value FROM (SELECT DISTINCT doc_id AS row FROM a), range({k}) r(topic))")
    return out, k, iters


def updates(kind: str, iters: int = 2, k: int = 2) -> str:
    """Multiplicative or gradient updates, unrolled for two topics."""
    out, _, _ = starts(iters, k)
    for i in range(1, iters + 1):
        for new, old, f, side in ((f"v{i}", f"v{i - 1}", f"u{i - 1}", "v"), (f"u{i}", f"u{i - 1}", f"v{i}", "u")):
            own, to = ("term", "doc_id") if side == "v" else ("doc_id", "term")
            out += [
                wide(f"{new}_w", f, k), f"{new}_g AS (SELECT sum(w0 * w0) AS g00, sum(w0 * w1) AS g01, sum(w1 * w1) AS g11 FROM {new}_w)",
                f"{new}_p AS (SELECT a.{to} AS row, f.topic, sum(a.x * f.value) AS b FROM a JOIN {f} f ON a.{own} = f.row GROUP BY ALL)",
                wide(f"{new}_o", old, k), wide(f"{new}_q", f"(SELECT row, topic, b AS value FROM {new}_p)", k),
            ]
            d = ["(o.w0 * g00 + o.w1 * g01)", "(o.w0 * g01 + o.w1 * g11)"]
            if kind == "multiplicative":
                cells = [f"o.w{t} * q.w{t} / greatest({d[t]}, 1e-12)" for t in range(k)]
            else:
                rate = "(2 * (1.0::DOUBLE / (2 * greatest((g00 + g11 + sqrt((g00 - g11) * (g00 - g11) + 4 * g01 * g01)) / 2, 1e-12))))"
                cells = [f"greatest(o.w{t} - {rate} * ({d[t]} - q.w{t}), 0)" for t in range(k)]
            out.append(f"{new} AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT row, {t} AS topic, {c} AS value FROM {new}_o o JOIN {new}_q q USING (row), {new}_g" for t, c in enumerate(cells)) + ")")
    return "WITH " + ", ".join(out)


def plsa(iters: int = 2) -> str:
    out, k, _ = starts(iters)
    out += [
        "pu0 AS (SELECT row, topic, value / sum(value) OVER (PARTITION BY topic) AS value FROM u0)",
        "pv0 AS (SELECT row, topic, value / sum(value) OVER (PARTITION BY row) AS value FROM v0)",
    ]
    for i in range(1, iters + 1):
        out += [
            f"z{i} AS MATERIALIZED (SELECT a.term, a.doc_id, p.topic, a.tf * p.value * q.value / sum(p.value * q.value) OVER (PARTITION BY a.term, a.doc_id) AS c FROM a "
            f"JOIN pu{i - 1} p ON p.row = a.term JOIN pv{i - 1} q ON q.row = a.doc_id AND q.topic = p.topic)",
            f"pu{i} AS (SELECT term AS row, topic, sum(c) / sum(sum(c)) OVER (PARTITION BY topic) AS value FROM z{i} GROUP BY term, topic)",
            f"pv{i} AS (SELECT doc_id AS row, topic, sum(c) / sum(sum(c)) OVER (PARTITION BY doc_id) AS value FROM z{i} GROUP BY doc_id, topic)",
        ]
    return "WITH " + ", ".join(out)
