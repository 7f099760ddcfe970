"""SQL for another engine that gives the same rows as the queries of :mod:`ctxloom.plans.relational`."""

from __future__ import annotations

from ctxloom.functions.symbols import EVENT_TYPES, ROLES, TEXT_ALPHABET, VOWELS

_ALPHA = TEXT_ALPHABET.replace("\n", "' || chr(10) || '")
_TYPES = ", ".join(f"'{x}'" for x in EVENT_TYPES)
_ROLES = ", ".join(f"'{x}'" for x in ROLES)
EV = f"(list_position([{_TYPES}], event_type) - 1)"
VAL = "least(floor(value / 12), 41)::INT"

SYM42 = f"""sym AS (SELECT doc_id AS k, pos, CASE WHEN instr('{_ALPHA}', c) > 0 THEN instr('{_ALPHA}', c) - 1 ELSE 41 END AS s
  FROM (SELECT doc_id, unnest(string_split(lower(text), '')) AS c, unnest(range(length(text))) AS pos FROM documents))"""
SYM4 = f"""sym AS (SELECT doc_id AS k, lang, pos, CASE WHEN instr('{VOWELS}', lower(c)) > 0 THEN 0 WHEN regexp_matches(c, '\\p{{L}}') THEN 1
    WHEN c IN (' ', chr(9), chr(10), chr(11), chr(12), chr(13), chr(133), chr(160)) THEN 2 ELSE 3 END AS s
  FROM (SELECT doc_id, lang, unnest(string_split(text, '')) AS c, unnest(range(length(text))) AS pos FROM documents))"""
PAGE42 = f"""sym AS (SELECT page_id AS k, pos, CASE WHEN instr('{_ALPHA}', c) > 0 THEN instr('{_ALPHA}', c) - 1 ELSE 41 END AS s
  FROM (SELECT page_id, unnest(string_split(lower(substr(html, 1, 101)), '')) AS c, unnest(range(101)) AS pos FROM pages WHERE length(html) >= 101))"""
EMB16 = """sym AS (SELECT vec_id AS k, pos, floor((x::DOUBLE + 1) * 16)::INT AS s
  FROM (SELECT vec_id, unnest(embedding) AS x, unnest(range(len(embedding))) AS pos FROM embeddings))"""
EV5 = f"sym AS (SELECT user_id AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS pos, {EV} AS s FROM events)"
VAL42 = f"sym AS (SELECT user_id AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS pos, {VAL} AS s FROM events)"
QTY50 = "sym AS (SELECT l_orderkey AS k, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity) - 1 AS pos, (l_quantity - 1)::INT AS s FROM lineitem)"


def before(order: int, m: int, extra: str = "") -> str:
    """Windows: code of the previous values (nearest lowest), symbol."""
    lags = ", ".join(f"lag(s, {i}) OVER w AS p{i}" for i in range(1, order + 1)) or "0 AS p0"
    code = " + ".join(f"p{i}::BIGINT * {m ** (i - 1)}" for i in range(1, order + 1)) or "0::BIGINT"
    return f"win AS (SELECT k, pos, s, {code} AS ctx{extra} FROM (SELECT *, {lags} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos)) WHERE pos >= {order})"


COUNTS = "cnt AS (SELECT ctx, s AS sym, count(*)::BIGINT AS n FROM win GROUP BY ALL)"
RATE = "SELECT sum(n)::BIGINT AS n, count(*) AS contexts, round(sum(n * log2(n) - g) / sum(n) + 0.0, 6) AS bpv FROM (SELECT ctx, sum(n) AS n, sum(n * log2(n)) AS g FROM cnt GROUP BY ctx)"


def rated(source: str, window: str) -> str:
    return f"WITH {source}, {window}, {COUNTS} {RATE}"


def own_window(code: str, start: int = 0, inner: str = "") -> str:
    return f"win AS (SELECT k, pos, s, {code} AS ctx FROM (SELECT *{inner} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos), b AS (PARTITION BY k ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)) WHERE pos >= {start})"


def orders() -> str:
    parts = []
    for order in range(9):
        code = " + ".join(f"p{i} * {4 ** (i - 1)}" for i in range(1, order + 1)) or "0"
        parts.append(f"SELECT {order} AS ord, {code} AS ctx, s FROM l WHERE pos >= {order}")
    lags = ", ".join(f"lag(s, {i}) OVER w AS p{i}" for i in range(1, 9))
    return f"""WITH {SYM4}, l AS (SELECT *, {lags} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos)),
      win AS ({' UNION ALL '.join(parts)}), cnt AS (SELECT ord, ctx, s, count(*) AS n FROM win GROUP BY ALL),
      per AS (SELECT ord, ctx, sum(n) AS n, sum(n * log2(n)) AS g FROM cnt GROUP BY ALL)
      SELECT ord, sum(n)::BIGINT AS n, count(*) AS contexts, round(sum(n * log2(n) - g) / sum(n) + 0.0, 6) AS bpv FROM per GROUP BY ord"""


def low_bits() -> str:
    parts = [f"SELECT {d} AS drop, ctx >> {d} AS ctx, s FROM win" for d in range(5)]
    return f"""WITH {SYM42}, {before(1, 42)}, cut AS ({' UNION ALL '.join(parts)}), cnt AS (SELECT "drop", ctx, s, count(*) AS n FROM cut GROUP BY ALL),
      per AS (SELECT "drop", ctx, sum(n) AS n, sum(n * log2(n)) AS g FROM cnt GROUP BY ALL)
      SELECT "drop", sum(n)::BIGINT AS n, count(*) AS contexts, round(sum(n * log2(n) - g) / sum(n) + 0.0, 6) AS bpv FROM per GROUP BY "drop\""""


def overfit(source: str, m: int) -> str:
    return f"""WITH {source}, {before(1, m)}, c AS (SELECT ctx, s, count(*) FILTER (k % 2 = 0) AS n0, count(*) FILTER (k % 2 = 1) AS n1 FROM win GROUP BY ALL),
      t AS (SELECT *, sum(n0) OVER (PARTITION BY ctx) AS t0, sum(n1) OVER (PARTITION BY ctx) AS t1 FROM c)
      SELECT sum(n0 + n1)::BIGINT AS n, round(sum((n0 + n1) * log2((t0 + t1) / (n0 + n1))) / sum(n0 + n1) + 0.0, 6) AS training,
        round(sum(n0 * log2((t1 + {m}.0) / (n1 + 1.0)) + n1 * log2((t0 + {m}.0) / (n0 + 1.0))) / sum(n0 + n1), 6) AS held_out FROM t"""


def merges(source: str, order: int, m: int) -> str:
    """Shared part: joint counts, their sum, and n lg n."""
    return f"{source}, {before(order, m)}, {COUNTS}, tot AS (SELECT sum(n)::DOUBLE AS t FROM cnt)"


def pair_costs(source: str, order: int, m: int) -> str:
    return f"""WITH {merges(source, order, m)}, ex AS (SELECT ctx, sum(n) * log2(sum(n)) - sum(n * log2(n)) AS e FROM cnt GROUP BY ctx),
      pr AS (SELECT a.ctx AS ctx_a, b.ctx AS ctx_b, a.e AS ea, b.e AS eb FROM ex a JOIN ex b ON a.ctx < b.ctx),
      su AS (SELECT ctx_a, ctx_b, ea, eb, sym, sum(n) AS n FROM pr JOIN cnt ON cnt.ctx = ctx_a OR cnt.ctx = ctx_b GROUP BY ALL)
      SELECT ctx_a, ctx_b, round((sum(n) * log2(sum(n)) - sum(n * log2(n)) - any_value(ea) - any_value(eb)) / (SELECT t FROM tot) + 0.0, 6) AS delta FROM su GROUP BY ctx_a, ctx_b"""


def tree(source: str, m: int) -> str:
    """The greedy tree by a recursion that carries the list of live sets (bit masks)."""
    return f"""{merges(source, 1, m)}, mk AS (SELECT unnest(range(1, {2**m})) AS mask),
      ms AS (SELECT mask, sym, sum(n) AS n FROM mk JOIN cnt ON (mask >> ctx) & 1 = 1 GROUP BY ALL),
      ex AS (SELECT mask, sum(n) * log2(sum(n)) - sum(n * log2(n)) AS e FROM ms GROUP BY mask),
      dl AS (SELECT x.mask AS a, y.mask AS b, greatest((z.e - x.e - y.e) / (SELECT t FROM tot), 0.0) AS d FROM ex x JOIN ex y ON x.mask < y.mask AND x.mask & y.mask = 0 JOIN ex z ON z.mask = x.mask | y.mask),
      steps AS (
        SELECT 0 AS step, (SELECT list(1::BIGINT << ctx::INT) FROM (SELECT DISTINCT ctx FROM cnt)) AS live, 0::BIGINT AS a, 0::BIGINT AS b, 0.0::DOUBLE AS d
        UNION ALL
        SELECT step + 1, list_append(list_filter(live, lambda x: x <> best.a AND x <> best.b), best.a | best.b), best.a, best.b, best.d
        FROM (SELECT step, live, (SELECT min({{'d': dl.d, 'a': dl.a, 'b': dl.b}}) FROM dl WHERE list_contains(steps.live, dl.a) AND list_contains(steps.live, dl.b)) AS best FROM steps WHERE len(live) > 1))"""


def events_fold(body: str) -> str:
    return f"WITH {EV5}, seq AS (SELECT k AS user_id, list(s ORDER BY pos) AS syms FROM sym GROUP BY k) {body}"


_TOP, _M = 1 << 15, 5
_TARGET = f"list_transform(range({_M + 1}), lambda j: CASE WHEN j <= x THEN j ELSE {_TOP - _M} + j END)"
_UNIFORM = "[" + ", ".join(str((j << 15) // 5) for j in range(6)) + "]"


def cdf_recursion(by_context: bool) -> str:
    """Row by row: the function of the row's context before the symbol, by a recursion over positions per user."""
    ctx = "coalesce(lag(s) OVER (PARTITION BY k ORDER BY pos), -1)" if by_context else "0"
    start = 1 if by_context else 0
    return f"""RECURSIVE {EV5}, r AS (SELECT k, pos, s, {ctx} AS c FROM sym), o AS (SELECT k, c, s, row_number() OVER (PARTITION BY k, c ORDER BY pos) AS i FROM r WHERE pos >= {start}),
      f AS (SELECT k, c, 0::BIGINT AS i, {_UNIFORM}::BIGINT[] AS cdf, 0.0::DOUBLE AS bits FROM (SELECT DISTINCT k, c FROM o)
        UNION ALL
        SELECT f.k, f.c, o.i, list_transform(range(6), lambda j: f.cdf[j + 1] + (((CASE WHEN j <= o.s THEN j ELSE {_TOP - _M} + j END) - f.cdf[j + 1]) >> 4)),
          f.bits + 15 - log2((f.cdf[o.s + 2] - f.cdf[o.s + 1])::DOUBLE) FROM f JOIN o ON o.k = f.k AND o.c = f.c AND o.i = f.i + 1),
      z AS (SELECT k, c, max(i) AS n, arg_max(cdf, i) AS cdf, arg_max(bits, i) AS bits FROM f GROUP BY k, c)"""


def doc_bits() -> str:
    """Bits of each document under the pooled order-1 class model with 0.5 added to every cell."""
    return f"""{SYM4}, {before(1, 4)}, {COUNTS}, grid AS (SELECT a.i AS ctx, b.i AS sym FROM range(4) a(i), range(4) b(i)),
      md AS (SELECT ctx, sym, log2(sum(coalesce(n, 0) + 0.5) OVER (PARTITION BY ctx) / (coalesce(n, 0) + 0.5)) AS bits FROM grid LEFT JOIN cnt USING (ctx, sym)),
      sm AS (SELECT k, count(*) AS n, round(sum(bits), 9) AS bits FROM win JOIN md ON md.ctx = win.ctx AND md.sym = win.s GROUP BY k),
      db AS (SELECT doc_id, lang, source, coalesce(n, 0)::BIGINT AS n, coalesce(bits, 0) AS bits FROM documents LEFT JOIN sm ON k = doc_id)"""


def menus() -> str:
    """Costs of six declared order-0 models for each user's events."""
    return f"""{EV5}, md AS (SELECT j, x, CASE WHEN j = 5 THEN -log2(0.2) WHEN j = x THEN -log2(0.5) ELSE -log2(0.125) END AS bits FROM range(6) a(j), range(5) b(x)),
      co AS (SELECT k % 3 AS file, k, j, sum(bits) AS bits FROM sym JOIN md ON md.x = sym.s GROUP BY ALL)"""


def kmeans() -> str:
    """Three rounds, unrolled: counts per user, models from pooled counts plus 0.5, cheapest model (lowest id on ties)."""
    parts = [
        f"{EV5}, {before(1, 5)}, rc AS (SELECT k, ctx, s AS sym, count(*) AS n FROM win GROUP BY ALL), grid AS (SELECT c.i AS cluster, a.i AS ctx, b.i AS sym FROM range(3) c(i), range(5) a(i), range(5) b(i))",
        "ids AS (SELECT k, row_number() OVER (ORDER BY k) - 1 AS cluster FROM (SELECT DISTINCT k FROM sym)), p0 AS (SELECT cluster, ctx, sym, n FROM rc JOIN ids USING (k) WHERE cluster < 3)",
    ]
    for i in range(4):
        parts.append(f"m{i} AS (SELECT cluster, ctx, sym, log2(sum(coalesce(n, 0) + 0.5) OVER (PARTITION BY cluster, ctx) / (coalesce(n, 0) + 0.5)) AS bits FROM grid LEFT JOIN p{i} USING (cluster, ctx, sym))")
        parts.append(f"c{i} AS (SELECT k, cluster, round(sum(n * bits), 9) AS bits FROM rc JOIN m{i} USING (ctx, sym) GROUP BY ALL)")
        parts.append(f"a{i} AS (SELECT k, (min({{'b': bits, 'c': cluster}})).c AS cluster, min(bits) AS bits FROM c{i} GROUP BY k)")
        parts.append(f"p{i + 1} AS (SELECT cluster, ctx, sym, sum(n) AS n FROM rc JOIN a{i} USING (k) GROUP BY ALL)")
    return "WITH " + ", ".join(parts) + " SELECT cluster::INT AS cluster, count(*) AS reads, round(sum(bits), 4) AS bits FROM a3 GROUP BY cluster"


READS4 = f"{SYM4}, rd AS (SELECT k, lang, pos // 101 AS r, pos % 101 AS pos, s, max(pos) OVER (PARTITION BY k) AS last FROM sym), rr AS (SELECT *, lag(s) OVER (PARTITION BY k, r ORDER BY pos) AS ctx FROM rd WHERE r * 101 + 100 <= last)"

ORACLES: dict[str, str] = {
    "rate_order0_text42": rated(SYM42, before(0, 42)),
    "rate_order1_text42": rated(SYM42, before(1, 42)),
    "rate_order2_text42": rated(SYM42, before(2, 42)),
    "rate_order3_class4": rated(SYM4, before(3, 4)),
    "rate_orders_class4": orders(),
    "joint_counts_class4": f"WITH {SYM4}, {before(2, 4)}, {COUNTS} SELECT ctx, sym, n FROM cnt",
    "padded_counts_class4": f"WITH {SYM4}, win AS (SELECT s, coalesce(lag(s) OVER (PARTITION BY k ORDER BY pos), 4)::BIGINT AS ctx FROM sym), {COUNTS} SELECT ctx, sym, n FROM cnt",
    "conditional_model_class4": f"WITH {SYM4}, {before(1, 4)}, {COUNTS}, t AS (SELECT *, sum(n) OVER (PARTITION BY ctx)::BIGINT AS n_ctx FROM cnt) SELECT ctx, sym, n, n_ctx, round(n / n_ctx, 6) AS p, round(log2(n_ctx / n), 6) AS bits FROM t",
    "smoothed_model_class4": f"WITH {SYM4}, {before(3, 4)}, {COUNTS}, g AS (SELECT a.i AS ctx, b.i AS sym FROM range(64) a(i), range(4) b(i)), f AS (SELECT ctx, sym, coalesce(n, 0) + 0.5 AS n FROM g LEFT JOIN cnt USING (ctx, sym)), t AS (SELECT *, sum(n) OVER (PARTITION BY ctx) AS nc FROM f) SELECT ctx, sym, round(n / nc, 6) AS p, round(log2(nc / n), 6) AS bits FROM t",
    "entropy_sources": "WITH c AS (SELECT count(*) AS n FROM documents GROUP BY source) SELECT round((sum(n) * log2(sum(n)) - sum(n * log2(n))) / sum(n) + 0.0, 6) AS entropy FROM c",
    "cross_entropy_langs": f"""WITH {SYM42}, {before(1, 42)}, c AS (SELECT lang, ctx, s AS sym, count(*) AS n FROM win JOIN documents ON doc_id = k GROUP BY ALL),
      g AS (SELECT a.i AS ctx, b.i AS sym FROM range(42) a(i), range(42) b(i)), f AS (SELECT g.ctx, g.sym, coalesce(n, 0) + 0.5 AS n FROM g LEFT JOIN c ON c.ctx = g.ctx AND c.sym = g.sym AND lang = 'en'),
      e AS (SELECT *, log2(sum(n) OVER (PARTITION BY ctx) / n) AS bits FROM f) SELECT lang, sum(c.n)::BIGINT AS n, round(sum(c.n * bits) / sum(c.n), 6) AS bpv FROM c JOIN e USING (ctx, sym) GROUP BY lang""",
    "low_bits_curve": low_bits(),
    "position_rate_page101": rated(PAGE42, own_window("pos")),
    "position_rate_emb16": rated(EMB16, own_window("pos")),
    "position_prev_rate": rated(PAGE42, own_window("pos + 101 * p", 1, ", lag(s) OVER w AS p")),
    "coarse_position_rate": rated(PAGE42, own_window("least(pos // 10, 7)")),
    "change_count_rate": f"""WITH {EV5}, x AS (SELECT *, lag(s) OVER (PARTITION BY k ORDER BY pos) AS p FROM sym), win AS (SELECT s, pos, p,
        least(coalesce(sum((p <> s)::INT) OVER (PARTITION BY k ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // 4, 7) + 8 * p AS ctx FROM x),
      cnt AS (SELECT ctx, s AS sym, count(*) AS n FROM win WHERE pos >= 1 GROUP BY ALL) {RATE}""",
    "running_sum_rate": rated(EV5, own_window("least(coalesce(t, 0) // 16, 7)", 0, ", sum(s) OVER b AS t")),
    "overfit_text42_order1": overfit(SYM42, 42),
    "overfit_val42_order1": overfit(VAL42, 42),
    "overfit_qty50_order1": overfit(QTY50, 50),
    "pair_merge_costs_ev5": pair_costs(EV5, 1, 5),
    "pair_merge_costs_class4": pair_costs(SYM4, 2, 4),
    "greedy_tree_ev5": f"WITH RECURSIVE {tree(EV5, 5)} SELECT step::INT AS step, a, b, round(d + 0.0, 6) AS delta, round(sum(d) OVER (ORDER BY step) + 0.0, 6) AS loss FROM steps WHERE step > 0",
    "greedy_tree_class4": f"WITH RECURSIVE {tree(SYM4, 4)} SELECT step::INT AS step, a, b, round(d + 0.0, 6) AS delta, round(sum(d) OVER (ORDER BY step) + 0.0, 6) AS loss FROM steps WHERE step > 0",
    "bins_ev5_k3": f"""WITH RECURSIVE {tree(EV5, 5)}, sets AS (SELECT unnest(live) AS mask FROM steps WHERE len(live) = 3), b AS (SELECT ctx, mask FROM sets JOIN (SELECT DISTINCT ctx FROM cnt) ON (mask >> ctx) & 1 = 1)
      SELECT ctx, (dense_rank() OVER (ORDER BY f) - 1)::INT AS bin FROM (SELECT ctx, min(ctx) OVER (PARTITION BY mask) AS f FROM b)""",
    "binned_rate_class4": f"""WITH RECURSIVE {tree(SYM4, 4)}, sets AS (SELECT len(live) AS bins, unnest(live) AS mask FROM steps) SELECT bins::INT AS bins, (SELECT t FROM tot)::BIGINT AS n, round(sum(e) / (SELECT t FROM tot) + 0.0, 6) AS bpv FROM sets JOIN ex USING (mask) GROUP BY bins""",
    "applied_bins_ev5": f"SELECT ([0, 1, 0, 1, 2])[{EV} + 1] AS bin, count(*) AS n FROM events GROUP BY 1",
    "pack_pair_counts": f"SELECT (({VAL} << 3) | {EV})::INT AS packed, any_value({VAL}) AS high, any_value({EV}) AS low, count(*) AS n FROM events GROUP BY 1",
    "pack_gain": f"""WITH p AS (SELECT {EV} AS a, {VAL} AS b, count(*) AS n FROM events GROUP BY ALL), x AS (SELECT n, sum(n) OVER (PARTITION BY a) AS na, sum(n) OVER (PARTITION BY b) AS nb FROM p),
      h AS (SELECT sum(n)::BIGINT AS n, log2(sum(n)) - sum(n * log2(na)) / sum(n) AS ha, log2(sum(n)) - sum(n * log2(nb)) / sum(n) AS hb, log2(sum(n)) - sum(n * log2(n)) / sum(n) AS hab FROM x)
      SELECT n, round(ha, 6) AS h_a, round(hb, 6) AS h_b, round(hab, 6) AS h_ab, round(ha + hb - hab, 6) AS gain FROM h""",
    "grouped_pairs_rate": f"""WITH {SYM4}, q AS (SELECT k, pos // 2 AS pos, sum(s * CASE WHEN pos % 2 = 0 THEN 4 ELSE 1 END)::INT AS s, count(*) AS c FROM sym GROUP BY k, pos // 2), sym2 AS (SELECT k, pos, s FROM q WHERE c = 2),
      win AS (SELECT k, pos, s, p AS ctx FROM (SELECT *, lag(s) OVER (PARTITION BY k ORDER BY pos) AS p FROM sym2) WHERE pos >= 1), {COUNTS} {RATE}""",
    "chain_state_rate_class4": rated(SYM4, own_window("p1 + 4 * (p2 >= 2)::INT", 2, ", lag(s) OVER w AS p1, lag(s, 2) OVER w AS p2")),
    "nested_pair_rate_fixed": rated(SYM4, own_window("(p1 >= 2)::INT + 2 * (p2 >= 2)::INT + 4 * (p3 >= 2)::INT + 8 * (p4 >= 2)::INT", 4, ", lag(s) OVER w AS p1, lag(s, 2) OVER w AS p2, lag(s, 3) OVER w AS p3, lag(s, 4) OVER w AS p4")),
    "counter_machine_rate": f"""WITH {EV5}, x AS (SELECT *, coalesce(lag(s) OVER (PARTITION BY k ORDER BY pos), 0) AS p FROM sym), win AS (SELECT k, pos, s,
        least(coalesce(sum((p <> s)::INT) OVER (PARTITION BY k ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0), 7) * 5 + p AS ctx FROM x),
      cnt AS (SELECT ctx, s AS sym, count(*) AS n FROM win WHERE pos >= 1 GROUP BY ALL) {RATE}""",
    "read_costs_fixed_models": f"""WITH {READS4}, c AS (SELECT k, lang, r, ctx, s AS sym, count(*) AS n FROM rr WHERE pos > 0 GROUP BY ALL), lc AS (SELECT lang, ctx, sym, sum(n) AS n FROM c GROUP BY ALL),
      lg AS (SELECT lang, dense_rank() OVER (ORDER BY lang) - 1 AS cluster FROM (SELECT DISTINCT lang FROM lc)), g AS (SELECT lang, cluster, a.i AS ctx, b.i AS sym FROM lg, range(4) a(i), range(4) b(i)),
      m AS (SELECT cluster, ctx, sym, log2(sum(coalesce(n, 0) + 0.5) OVER (PARTITION BY cluster, ctx) / (coalesce(n, 0) + 0.5)) AS bits FROM g LEFT JOIN lc USING (lang, ctx, sym)),
      t AS (SELECT k, lang, r, cluster, round(sum(n * bits), 9) AS bits FROM c JOIN m USING (ctx, sym) GROUP BY ALL), b AS (SELECT k, lang, r, min({{'b': bits, 'c': cluster}}) AS best FROM t GROUP BY ALL)
      SELECT lang, best.c::INT AS cluster, count(*) AS reads, round(sum(best.b), 3) AS bits FROM b GROUP BY ALL""",
    "kmeans_3_rounds": kmeans(),
    "header_cost": "WITH c AS (SELECT sum(length(text) // 101) AS n FROM documents GROUP BY lang HAVING n > 0) SELECT round(2.0 / 101, 6) AS flat_bpv, round((sum(n) * log2(sum(n)) - sum(n * log2(n))) / (sum(n) * 101) + 0.0, 6) AS entropy_bpv FROM c",
    "order_bits": "SELECT (SELECT count(*) FROM documents) AS reads, round(sum(log2(i)), 4) AS bits FROM range(1, (SELECT count(*) + 1 FROM documents)) r(i)",
    "menu_greedy": f"""WITH {menus()}, s1 AS (SELECT file, j, round(sum(bits), 6) AS b FROM co GROUP BY ALL), q1 AS (SELECT file, (min({{'b': b, 'j': j}})).j AS j1 FROM s1 GROUP BY file),
      f1 AS (SELECT co.file, k, j1, bits AS b1 FROM co JOIN q1 ON q1.file = co.file AND j = j1), s2 AS (SELECT co.file, j1, j, round(sum(least(b1, bits)), 6) AS b FROM co JOIN f1 USING (file, k) GROUP BY ALL),
      q2 AS (SELECT file, j1, min({{'b': b, 'j': j}}) AS x FROM s2 GROUP BY ALL) SELECT file, list_sort([j1, x.j])::INT[] AS menu, round(x.b, 4) AS bits FROM q2""",
    "menu_best_pair": f"""WITH {menus()}, p AS (SELECT a.file, a.j AS j1, b.j AS j2, round(sum(least(a.bits, b.bits)), 6) AS b FROM co a JOIN co b ON a.k = b.k AND a.j < b.j GROUP BY ALL),
      q AS (SELECT file, min({{'b': b, 'i': j1, 'j': j2}}) AS x FROM p GROUP BY file) SELECT file, [x.i, x.j]::INT[] AS menu, round(x.b, 4) AS bits FROM q""",
    "ema_events": "WITH v AS (SELECT user_id, list(value ORDER BY ts, event_id) AS v FROM events GROUP BY user_id) SELECT user_id, round(list_reduce(list_prepend(0.0::DOUBLE, v), lambda a, x: a * 0.9::DOUBLE + x * (1 - 0.9::DOUBLE)), 6) AS ema FROM v",
    "ema_location_scale": f"""WITH RECURSIVE o AS (SELECT user_id, value AS x, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events),
      f AS (SELECT user_id, 0::BIGINT AS i, x AS c, 0.0::DOUBLE AS s FROM o WHERE i = 1 UNION ALL SELECT f.user_id, o.i, c * 0.9::DOUBLE + x * (1 - 0.9::DOUBLE), s * 0.9::DOUBLE + abs(x - c) * (1 - 0.9::DOUBLE) FROM f JOIN o ON o.user_id = f.user_id AND o.i = f.i + 1)
      SELECT user_id, round(arg_max(c, i), 6) AS centre, round(arg_max(s, i), 6) AS scale FROM f GROUP BY user_id""",
    "ema_eta_grid": """WITH RECURSIVE o AS (SELECT user_id, value AS x, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events), e AS (SELECT unnest([0.5, 0.8, 0.9, 0.95, 0.99])::DOUBLE AS eta),
      f AS (SELECT user_id, eta, 0::BIGINT AS i, 0.0::DOUBLE AS v, 0.0::DOUBLE AS q FROM (SELECT DISTINCT user_id FROM o), e
        UNION ALL SELECT f.user_id, eta, o.i, v * eta + x * (1 - eta), (x - v) * (x - v) FROM f JOIN o ON o.user_id = f.user_id AND o.i = f.i + 1)
      SELECT eta, round(avg(q), 4) AS mse FROM f WHERE i > 0 GROUP BY eta""",
    "cdf_shift_events": f"WITH {cdf_recursion(False)} SELECT k AS user_id, " + ", ".join(f"cdf[{i + 1}]::INT AS c{i}" for i in range(1, 5)) + " FROM z",
    "adaptive_order0_ev5": f"WITH {cdf_recursion(False)} SELECT k AS user_id, round(bits, 6) AS bits FROM z",
    "adaptive_order1_ev5": f"WITH {cdf_recursion(True)} SELECT u.k AS user_id, coalesce(sum(n), 0)::BIGINT AS n, round(coalesce(sum(bits), 0), 6) AS bits FROM (SELECT DISTINCT k FROM sym) u LEFT JOIN z ON z.k = u.k GROUP BY u.k",
    "half_life_table": """SELECT rate, docs, round(1 - pow(2.0, -rate), 9) AS eta, round(-1 / log2(1 - pow(2.0, -rate)), 6) AS half_life
      FROM (SELECT (length(bin(length(text))) - 1)::INT AS rate, count(*) AS docs FROM documents WHERE length(text) >= 2 GROUP BY 1)""",
    "rle_runs_role": f"""WITH s AS (SELECT conv_id AS k, turn AS pos, list_position([{_ROLES}], role) - 1 AS s FROM conversations), n AS (SELECT *, (s IS DISTINCT FROM lag(s) OVER (PARTITION BY k ORDER BY pos))::INT AS f FROM s),
      r AS (SELECT *, sum(f) OVER (PARTITION BY k ORDER BY pos) AS run FROM n), q AS (SELECT k, run, any_value(s) AS sym, count(*) AS length FROM r GROUP BY k, run) SELECT sym, length, count(*) AS n FROM q GROUP BY ALL""",
    "rle_runs_class4": f"WITH {SYM4}, n AS (SELECT *, (s IS DISTINCT FROM lag(s) OVER (PARTITION BY k ORDER BY pos))::INT AS f FROM sym), r AS (SELECT *, sum(f) OVER (PARTITION BY k ORDER BY pos) AS run FROM n), q AS (SELECT k, run, any_value(s) AS sym, count(*) AS length FROM r GROUP BY k, run) SELECT sym, length, count(*) AS n FROM q GROUP BY ALL",
    "rle_rate_class4": f"""WITH {SYM4}, n AS (SELECT *, (s IS DISTINCT FROM lag(s) OVER (PARTITION BY k ORDER BY pos))::INT AS f FROM sym), r AS (SELECT *, sum(f) OVER (PARTITION BY k ORDER BY pos) AS run FROM n), q AS (SELECT k, run, any_value(s) AS sym, count(*) AS length FROM r GROUP BY k, run),
      c AS (SELECT sym, length, count(*) AS n FROM q GROUP BY ALL) SELECT sum(n)::BIGINT AS runs, sum(n * length)::BIGINT AS n, round((sum(n) * log2(sum(n)) - sum(n * log2(n))) / sum(n * length) + 0.0, 6) AS bpv FROM c""",
    "cube_bits": f"WITH {doc_bits()} SELECT lang, source, sum(n)::BIGINT AS n, round(sum(bits) / sum(n), 6) AS bpv FROM db GROUP BY CUBE (lang, source)",
    "rollup_bits": f"WITH {doc_bits()} SELECT lang, source, count(*) AS docs, round(sum(bits) / sum(n), 6) AS bpv FROM db GROUP BY ROLLUP (lang, source)",
    "topk_reads": f"WITH {doc_bits()}, r AS (SELECT lang, doc_id, round(bits / n, 6) AS bpv, row_number() OVER (PARTITION BY lang ORDER BY round(bits / n, 6) DESC, doc_id) AS place FROM db WHERE n > 0) SELECT lang, place::INT AS place, doc_id, bpv FROM r WHERE place <= 3",
    "unseen_contexts_anti": f"WITH {SYM42}, {before(2, 42)} SELECT ctx, count(*) AS n FROM win WHERE k % 2 = 1 AND ctx NOT IN (SELECT ctx FROM win WHERE k % 2 = 0) GROUP BY ctx",
    "hourly_rate": f"WITH c AS (SELECT hour(ts) AS h, {EV} AS s, count(*) AS n FROM events GROUP BY ALL) SELECT h::INT AS hour, sum(n)::BIGINT AS n, round((sum(n) * log2(sum(n)) - sum(n * log2(n))) / sum(n) + 0.0, 6) AS bpv FROM c GROUP BY h",
    "asof_model": "WITH v AS (SELECT user_id, ts, event_id AS version FROM events WHERE event_id % 10 = 0) SELECT e.user_id, v.version, count(*) AS n FROM events e ASOF LEFT JOIN v ON e.user_id = v.user_id AND e.ts >= v.ts GROUP BY ALL",
    "block_of_events": "SELECT b.i::INT AS block, count(*) AS n FROM events JOIN range(12) b(i) ON value >= b.i * 60 AND value < (b.i + 1) * 60 GROUP BY 1",
    "quality_by_rate": f"WITH {doc_bits()} SELECT quality, count(*) AS docs, round(sum(bits) / sum(n), 6) AS bpv FROM db JOIN labels USING (doc_id) GROUP BY quality",
    "event_props_rate": f"WITH c AS (SELECT (props::JSON ->> 'k')::BIGINT % 8 AS ctx, {EV} AS sym, count(*) AS n FROM events GROUP BY ALL), cnt AS (SELECT * FROM c) {RATE}",
    "star_revenue_top": "SELECT c_mktsegment, l_returnflag, l_linestatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY ALL",
    "context_overlap": f"""WITH {SYM4}, {before(3, 4)}, a AS (SELECT DISTINCT ctx FROM win WHERE k % 2 = 0), b AS (SELECT DISTINCT ctx FROM win WHERE k % 2 = 1)
      SELECT 'both' AS kind, count(*) AS n FROM a JOIN b USING (ctx) UNION ALL SELECT 'even only', count(*) FROM a WHERE ctx NOT IN (SELECT ctx FROM b) UNION ALL SELECT 'odd only', count(*) FROM b WHERE ctx NOT IN (SELECT ctx FROM a)""",
    "pivot_types_by_hour": "SELECT hour(ts)::INT AS hour, " + ", ".join(f"count(*) FILTER (event_type = '{x}') AS {x}" for x in EVENT_TYPES) + " FROM events GROUP BY 1",
    "bits_percentiles": f"WITH {doc_bits()} SELECT lang, " + ", ".join(f"round(quantile_cont(bits / n, {p}), 6) AS p{int(p * 100)}" for p in (0.1, 0.5, 0.9)) + " FROM db WHERE n > 0 GROUP BY lang",
    "session_lengths": """WITH g AS (SELECT user_id, ts, event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events),
      m AS (SELECT user_id, sum((coalesce(gap, 1152921504606846976) > 2592000000000)::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM g),
      c AS (SELECT user_id, session, count(*) AS events FROM m GROUP BY ALL) SELECT events, count(*) AS sessions FROM c GROUP BY events""",
    "added_counts_class4": f"WITH {SYM4}, {before(1, 4)} SELECT ctx, s AS sym, count(*) AS n FROM win WHERE k % 2 = 0 GROUP BY ALL",
}
