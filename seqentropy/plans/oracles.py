"""SQL builders: the same computations as the operators', for DuckDB on the same tables."""

from __future__ import annotations

import math

from ..functions.mathx import sql_digamma, sql_lgamma

LN2 = math.log(2)

#: Sequence sources as SQL: seq_id, t.
DOCS27 = "SELECT * FROM (SELECT doc_id AS seq_id, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS t FROM documents WHERE text IS NOT NULL) WHERE t <> ''"
BENCH27 = "SELECT * FROM (SELECT item_id AS seq_id, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS t FROM benchmark WHERE text IS NOT NULL) WHERE t <> ''"
TURNS27 = "SELECT * FROM (SELECT conv_id * 1000 + turn AS seq_id, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS t FROM conversations WHERE text IS NOT NULL) WHERE t <> ''"


def with_seqs(source: str) -> str:
    return f"seqs AS ({source})"


def places(source: str, left: int, by: str = "") -> str:
    """[by,] s, t, k, e: every position as the end e of a short piece t, which has the k <= left symbols before its start s (long strings are slow to index)."""
    b = f"{by}, " if by else ""
    return f"""SELECT {b}s, l || b AS t, len(l) AS k, unnest(range(len(l) + 1, len(l) + len(b) + 1)) AS e
  FROM (SELECT {b}s, substr(t, greatest(s - {left}, 1), s - greatest(s - {left}, 1)) AS l, substr(t, s, 256) AS b
  FROM (SELECT {b}t, unnest(range(1, len(t) + 1, 256)) AS s FROM ({source})))"""


def words(n_max: int, by: str = "") -> str:
    """counts([by,] n, word, cnt) from seqs."""
    b = f"{by}, " if by else ""
    return f"""ends AS ({places("SELECT * FROM seqs", n_max - 1, by)}),
words AS (SELECT {b}t, e, unnest(range(1, least({n_max}, e) + 1)) AS n FROM ends),
counts AS (SELECT {b}CAST(n AS INTEGER) AS n, substr(t, e - n + 1, n) AS word, count(*) AS cnt FROM words GROUP BY ALL)"""


def block_entropy(d: int, beta: float = 0.5, by: str = "") -> str:
    """h([by,] n, method, n_windows, n_words, h_block) in bits from counts."""
    b = f"{by}, " if by else ""
    psi = sql_digamma("cnt")
    return f"""spectrum AS (SELECT {b}n, CAST(cnt AS DOUBLE) AS cnt, CAST(count(*) AS DOUBLE) AS mult FROM counts GROUP BY ALL),
parts AS (SELECT {b}n, sum(cnt * mult) AS w, sum(mult) AS m, sum(mult * cnt * ln(cnt)) AS clogc,
  sum(mult * cnt * ({psi} + CASE WHEN cnt % 2 = 0 THEN 1.0 ELSE -1.0 END / (cnt * (cnt + 1)))) AS cpsi,
  sum(mult * (cnt + 1) * ln(cnt + 1)) AS laplace, sum(mult * (cnt + {beta}) * {sql_digamma(f'(cnt + {beta} + 1)')}) AS dirichlet, exp(n * ln({d}.0)) AS k
  FROM spectrum GROUP BY {b}n),
h AS (
  SELECT {b}n, 'plugin' AS method, w, m, (ln(w) - clogc / w) / {LN2!r} AS h_block FROM parts
  UNION ALL SELECT {b}n, 'first_order', w, m, (ln(w) - clogc / w + (m - 1) / (2 * w)) / {LN2!r} FROM parts
  UNION ALL SELECT {b}n, 'digamma_parity', w, m, (ln(w) - cpsi / w) / {LN2!r} FROM parts
  UNION ALL SELECT {b}n, 'laplace_block', w, m, (ln(w + k) - laplace / (w + k)) / {LN2!r} FROM parts
  UNION ALL SELECT {b}n, 'dirichlet_mean', w, m, ({sql_digamma(f'(w + {beta} * k + 1)')} - (dirichlet + (k - m) * {beta} * {sql_digamma(repr(beta + 1.0))}) / (w + {beta} * k)) / {LN2!r} FROM parts)"""


def events(order: int) -> str:
    """events(seq_id, pos, sym, past) from seqs."""
    return f"""events AS (SELECT seq_id, CAST(s + e - k - 1 AS BIGINT) AS pos, substr(t, e, 1) AS sym, substr(t, greatest(e - {order}, 1), e - greatest(e - {order}, 1)) AS past
  FROM ({places("SELECT * FROM seqs", order, "seq_id")}))"""


def line_events(order: int, seqs: str = "seqs", name: str = "events") -> str:
    """name(seq_id, pos, sym, past) from seqs with very long texts, cut in two steps."""
    o = order
    return f"""{name}_big AS (SELECT seq_id, s0, s0 - greatest(s0 - {o}, 1) AS k0, substr(t, greatest(s0 - {o}, 1), 8192 + s0 - greatest(s0 - {o}, 1)) AS t FROM (SELECT seq_id, t, unnest(range(1, len(t) + 1, 8192)) AS s0 FROM {seqs})),
{name}_cut AS (SELECT seq_id, s0 + s - k0 - 1 AS s1, s - greatest(s - {o}, 1) AS k1, substr(t, greatest(s - {o}, 1), 256 + s - greatest(s - {o}, 1)) AS t FROM (SELECT *, unnest(range(k0 + 1, len(t) + 1, 256)) AS s FROM {name}_big)),
{name} AS (SELECT seq_id, CAST(s1 + e - k1 - 1 AS BIGINT) AS pos, substr(t, e, 1) AS sym, substr(t, greatest(e - {o}, 1), e - greatest(e - {o}, 1)) AS past FROM (SELECT *, unnest(range(k1 + 1, len(t) + 1)) AS e FROM {name}_cut))"""


def trained(order: int) -> str:
    """nodes(depth, ctx, n, gain) and cells(depth, ctx, sym, cnt) after levels()."""
    rows = " UNION ALL ".join(f"SELECT {j} AS depth, key AS ctx, sym, count(*) AS cnt, sum({'CASE WHEN n > 0 THEN ln(p_up) - ln(p) ELSE 0.0 END' if j else '0.0'}) AS gain FROM e{j} WHERE alive GROUP BY key, sym" for j in range(order + 1))
    return f"cells AS MATERIALIZED ({rows}), nodes AS MATERIALIZED (SELECT depth, ctx, sum(cnt) AS n, round(sum(gain), 9) AS gain FROM cells GROUP BY depth, ctx)"


def mixture(depth: int, d: int) -> str:
    """w0(seq_id, w) from events(seq_id, sym, past): log probability of the half-and-half mixture over trees."""
    out = [f"ev AS (SELECT seq_id, sym, past FROM events WHERE len(past) = {depth})"]
    for j in range(depth, -1, -1):
        key = f"right(past, {j})" if j else "''"
        out.append(f"k{j} AS (SELECT seq_id, ctx, sum({sql_lgamma('c + 0.5')} - {sql_lgamma('0.5')}) - max({sql_lgamma(f'n + {0.5 * d}')} - {sql_lgamma(repr(0.5 * d))}) AS kt FROM (SELECT seq_id, ctx, sym, c, sum(c) OVER (PARTITION BY seq_id, ctx) AS n FROM (SELECT seq_id, {key} AS ctx, sym, count(*) AS c FROM ev GROUP BY ALL)) GROUP BY seq_id, ctx)")
        if j == depth:
            out.append(f"w{j} AS (SELECT seq_id, ctx, kt AS w FROM k{j})")
        else:
            below = f"SELECT seq_id, right(ctx, {j}) AS ctx, sum(w) AS w FROM w{j + 1} GROUP BY ALL" if j else f"SELECT seq_id, '' AS ctx, sum(w) AS w FROM w{j + 1} GROUP BY seq_id"
            out.append(f"w{j} AS (SELECT seq_id, ctx, ln(0.5) + greatest(kt, b.w) + ln(exp(kt - greatest(kt, b.w)) + exp(b.w - greatest(kt, b.w))) AS w FROM k{j} JOIN ({below}) b USING (seq_id, ctx))")
    return ", ".join(out)


def levels(order: int, d: int, beta: float, rule: str, delta: float = 0.0, tree: str = "full", q: float = 1.0, static: list[float] | None = None) -> str:
    """pred(seq_id, pos, sym, p) from events, a window query for each level."""
    out = [f"l_start AS (SELECT seq_id, pos, sym, past, CAST(-1 AS BIGINT) AS born, true AS alive, 0 AS run, 1.0 / {d} AS p_up, 1.0 / {d} AS res, false AS flag, 1.0 / {d} AS cand, false AS done, true AS going, 0.0 AS total, 0.0 AS best FROM events)"]
    prev = "l_start"
    for j in range(order + 1):
        key = f"CASE WHEN len(past) >= {j} THEN right(past, {j}) END" if j else "''"
        if j and tree == "incremental":
            out.append(f"a{j} AS (SELECT *, {key} AS key, min(CASE WHEN alive AND pos > born AND run >= 2 THEN pos END) OVER (PARTITION BY seq_id, {key}) AS birth FROM {prev})")
            out.append(f"b{j} AS (SELECT * REPLACE (coalesce(alive AND key IS NOT NULL AND pos >= birth, false) AS alive, coalesce(birth, born) AS born) FROM a{j})")
        else:
            out.append(f"b{j} AS (SELECT * REPLACE (({key}) IS NOT NULL AS alive), {key} AS key, NULL AS birth FROM {prev})")
        live = "CASE WHEN alive THEN 1 ELSE 0 END"
        over = "ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING"
        out.append(f"c{j} AS (SELECT *, coalesce(sum({live}) OVER (PARTITION BY seq_id, key {over}), 0) AS n, coalesce(sum({live}) OVER (PARTITION BY seq_id, key, sym {over}), 0) AS na FROM b{j})")
        out.append(f"d{j} AS (SELECT *, (na + {beta}) / (n + {beta * d}) AS p FROM c{j})")
        gain = f"round(coalesce(sum(CASE WHEN alive AND n > 0 THEN ln(p_up) - ln(p) ELSE 0.0 END) OVER (PARTITION BY seq_id, key {over}), 0.0), 9)" if j else "-1.0"
        out.append(f"e{j} AS (SELECT *, {gain} AS gain FROM d{j})")
        ok = "(alive AND n > 0)" if j else "true"
        good = f"({ok} AND gain < {-delta})"
        s = {"res": "res", "flag": "flag", "cand": "cand", "done": "done", "going": "going", "total": "total", "best": "best"}
        if rule == "fixed" and j == order:
            s["res"] = f"CASE WHEN alive THEN p ELSE 1.0 / {d} END"
        elif rule == "deepest":
            s["res"] = f"CASE WHEN {ok} THEN p ELSE res END"
        elif rule == "deepest_gain":
            s["res"] = f"CASE WHEN {good if j else ok} THEN p ELSE res END"
        elif rule == "walk_gain":
            s["going"] = f"(going AND {ok} AND gain <= 0)" if j else "true"
            s["res"] = f"CASE WHEN {good if j else ok} AND {s['going']} THEN p ELSE res END"
        elif rule == "min_total_gain":
            if j:
                s["total"] = f"CASE WHEN {ok} THEN total + gain ELSE total END"
                take = f"({ok} AND {s['total']} < best - {delta})"
                s["res"], s["best"] = f"CASE WHEN {take} THEN p ELSE res END", f"CASE WHEN {take} THEN {s['total']} ELSE best END"
            else:
                s["res"] = "p"
        elif rule == "shortest_gain":
            if j:
                end = f"(flag AND (NOT {ok} OR gain >= 0) AND NOT done)"
                s["res"], s["done"] = f"CASE WHEN {end} THEN cand ELSE res END", f"(done OR {end})"
            else:
                s["res"] = "p"
            s["flag"], s["cand"] = good, "CASE WHEN alive THEN p ELSE cand END"
        elif static is not None:
            s["cand"] = f"CASE WHEN {ok} THEN p ELSE cand END"
            s["res"] = f"({static[j]} * ({s['cand']}) + {'res' if j else '0.0'})"
        elif rule == "blend":
            e = f"(CASE WHEN alive AND n > 0 THEN {q} / (n + {q}) ELSE 1.0 END)"
            s["res"] = f"(1 - {e}) * p + {e} * res"
        out.append(f"f{j} AS (SELECT seq_id, pos, sym, past, born, alive, CASE WHEN alive THEN na + 1 ELSE 0 END AS run, CASE WHEN alive THEN p ELSE p_up END AS p_up, " + ", ".join(f"{v} AS {k}" for k, v in s.items()) + f" FROM e{j})")
        prev = f"f{j}"
    last = "CASE WHEN flag AND NOT done THEN cand ELSE res END" if rule == "shortest_gain" else "res"
    out.append(f"pred AS (SELECT seq_id, pos, sym, {last} AS p FROM {prev})")
    return ",\n".join(out)


RATE = f"SELECT count(*) AS n, round(sum(-ln(p)) / count(*) / {LN2!r}, 6) AS bits FROM pred"
