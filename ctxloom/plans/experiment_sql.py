"""SQL for another engine that gives the same rows as the experiments of :mod:`ctxloom.plans.workloads` and the method queries of
:mod:`ctxloom.plans.methods`: trees by a recursion over lists of live nodes, clusters by unrolled rounds, adaptive scans by
recursions over places."""

from __future__ import annotations

from ctxloom.functions.symbols import EVENT_TYPES, TEXT_ALPHABET
from ctxloom.plans.oracles import COUNTS, EV, EV5, EMB16, PAGE42, QTY50, SYM4, SYM42, VAL, VAL42, before

_ALPHA = TEXT_ALPHABET.replace("\n", "' || chr(10) || '")
_CODE42 = f"CASE WHEN instr('{_ALPHA}', c) > 0 THEN instr('{_ALPHA}', c) - 1 ELSE 41 END"
#: Reads of 101 symbols with their tails: k, r, pos (in the read), s.
READS42 = f"{SYM42}, rd AS (SELECT k, pos // 101 AS r, pos % 101 AS pos, s FROM sym)"
READS4 = f"{SYM4}, rd AS (SELECT k, pos // 101 AS r, pos % 101 AS pos, s FROM sym)"
PAGES42 = f"""psym AS (SELECT page_id AS k, pos, {_CODE42} AS s
  FROM (SELECT page_id, unnest(string_split(lower(html), '')) AS c, unnest(range(length(html))) AS pos FROM pages)), rd AS (SELECT k, pos // 101 AS r, pos % 101 AS pos, s FROM psym)"""
WORDLEN = r"""sym AS (SELECT doc_id AS k, unnest(range(len(w))) AS pos, unnest(list_transform(w, lambda x: least(length(x), 15))) AS s
  FROM (SELECT doc_id, list_filter(string_split_regex(text, '[ \t\n\x0B\f\r]+'), lambda x: x <> '') AS w FROM documents))"""


def draw(keys: list[str], seed: int = 0) -> str:
    text = " || '|' || ".join([*(f"coalesce({k}::VARCHAR, '')" for k in keys), f"'{seed}'"])
    return f"(('0x' || substr(md5({text}), 1, 12))::BIGINT::DOUBLE / {1 << 48}.0)"


def excess(r: str) -> str:
    return f"(CASE WHEN list_sum({r}) > 0 THEN list_sum({r}) * log2(list_sum({r})) ELSE 0 END - list_sum(list_transform({r}, lambda c: CASE WHEN c > 0 THEN c * log2(c) ELSE 0 END)))"


def grown(name: str, counts: str, m: int, by: str = "0", stop: int = 1, capacity: int = 0) -> str:
    """CTEs <name>_leaf (g, node, ctx, r, own), <name>_t (g, t) and <name>_steps (g, step, live, leaves, a, b, d) of the greedy trees of a
    count table (ctx, sym, n and perhaps a group). Live nodes are {node, lo, k, leaf, r, own}."""
    both = "list_transform(list_zip(x.r, y.r), lambda z: z[1] + z[2])"
    fits = f" AND x.k + y.k <= {capacity}" if capacity else ""
    return f"""{name}_in AS (SELECT {by} AS g, ctx, sym, n FROM {counts}),
      {name}_rows AS (SELECT c.g, c.ctx, list(coalesce(i.n, 0)::DOUBLE ORDER BY x.i) AS r FROM (SELECT DISTINCT g, ctx FROM {name}_in) c CROSS JOIN range({m}) x(i)
        LEFT JOIN {name}_in i ON i.g = c.g AND i.ctx = c.ctx AND i.sym = x.i GROUP BY c.g, c.ctx),
      {name}_leaf AS (SELECT g, row_number() OVER (PARTITION BY g ORDER BY ctx) - 1 AS node, ctx, r, {excess('r')} AS own FROM {name}_rows),
      {name}_t AS (SELECT g, sum(n)::DOUBLE AS t FROM {name}_in GROUP BY g),
      {name}_steps AS (
        SELECT g, 0::BIGINT AS step, list({{'node': node, 'lo': node, 'k': 1::BIGINT, 'leaf': [ctx], 'r': r, 'own': own}} ORDER BY node) AS live, count(*) AS leaves, 0::BIGINT AS a, 0::BIGINT AS b, 0.0::DOUBLE AS d FROM {name}_leaf GROUP BY g
        UNION ALL
        SELECT g, step + 1, list_append(list_filter(live, lambda x: x.node <> best.a AND x.node <> best.b),
          {{'node': leaves + step, 'lo': best.lo, 'k': best.k, 'leaf': best.leaf, 'r': best.r, 'own': {excess('best.r')}}}), leaves, best.a, best.b, best.d
        FROM (SELECT g, step, live, leaves, (SELECT min({{'d': d, 'a': a, 'b': b, 'lo': lo, 'k': k, 'leaf': leaf, 'r': r}}) FROM (
            SELECT x.node AS a, y.node AS b, least(x.lo, y.lo) AS lo, x.k + y.k AS k, list_concat(x.leaf, y.leaf) AS leaf, {both} AS r,
              greatest(({excess(both)} - x.own - y.own) / (SELECT t FROM {name}_t q WHERE q.g = o.g), 0) AS d
            FROM (SELECT unnest(o.live) AS x), (SELECT unnest(o.live) AS y) WHERE x.node < y.node{fits})) AS best FROM {name}_steps o WHERE len(live) > {stop}) WHERE best IS NOT NULL)"""


def at_bins(out: str, name: str, bins: int) -> str:
    """<out> (g, ctx, bin) where the tree has at most so many live nodes for the first time; bins are numbered by their least leaf."""
    return numbered(out, f"SELECT g, live FROM {name}_steps QUALIFY len(live) <= {bins} AND row_number() OVER (PARTITION BY g, len(live) <= {bins} ORDER BY step) = 1")


def within_loss(out: str, name: str, loss: float) -> str:
    """<out>, where the last merge whose running loss stays within the bound has been made."""
    return numbered(out, f"SELECT g, arg_max(live, step) AS live FROM (SELECT g, step, live, sum(d) OVER (PARTITION BY g ORDER BY step) AS loss FROM {name}_steps) WHERE loss <= {loss} + 1e-12 GROUP BY g")


def numbered(out: str, lives: str) -> str:
    return f"""{out} AS (SELECT g, unnest(x.leaf) AS ctx, bin FROM (SELECT g, x, row_number() OVER (PARTITION BY g ORDER BY x.lo) - 1 AS bin FROM (SELECT g, unnest(live) AS x FROM ({lives}))))"""


def rate_of(cells: str, by: str = "") -> str:
    """n, contexts, bpv of a relation of cells (by, ctx, sym, n)."""
    g, comma = (f" GROUP BY {by}", f"{by}, ") if by else ("", "")
    return f"""SELECT {comma}sum(n)::BIGINT AS n, count(*) AS contexts, round(sum(n * log2(n) - g) / sum(n) + 0.0, 6) AS bpv
      FROM (SELECT {comma}ctx, sum(n) AS n, sum(n * log2(n)) AS g FROM {cells} GROUP BY {comma}ctx){g}"""


def tree_of(source: str, order: int, m: int, tree: str = "tr", stop: int = 1) -> str:
    return f"WITH RECURSIVE {source}, {before(order, m)}, {COUNTS}, {grown(tree, 'cnt', m, stop=stop)}"


def binning(source: str, order: int, m: int) -> str:
    """none, complete, binned, ranges of as many bins, and a digest's order dealt into as many."""
    some = "SELECT m, (SELECT max(bin) + 1 FROM bn) AS bins"
    return f"""{tree_of(source, order, m)}, {within_loss('bn', 'tr', 0.01)}, kk AS (SELECT max(bin) + 1 AS k, (SELECT count(*) FROM tr_leaf) AS c FROM bn),
      alt AS (SELECT 'binned' AS measure, ctx, bin FROM bn UNION ALL SELECT 'range bins', ctx, node * k // c FROM tr_leaf, kk
        UNION ALL SELECT 'random bins', ctx, (row_number() OVER (ORDER BY md5(node::VARCHAR || '|0'), node) - 1) % k FROM tr_leaf, kk
        UNION ALL SELECT 'none', ctx, 0 FROM tr_leaf UNION ALL SELECT 'complete', ctx, node FROM tr_leaf),
      cl AS (SELECT measure, bin AS ctx, sym, sum(n) AS n FROM alt JOIN cnt USING (ctx) GROUP BY ALL)
      SELECT measure, contexts::INT AS bins, bpv FROM ({rate_of('cl', 'measure')})"""


ORACLES: dict[str, str] = {
    "merge_steps_text42": f"{tree_of(SYM42, 1, 42)} SELECT step::INT AS step, (leaves + step - 1)::INT AS node, a::INT AS \"left\", b::INT AS \"right\", round(d + 0.0, 6) AS delta, round(sum(d) OVER (ORDER BY step) + 0.0, 6) AS loss FROM tr_steps WHERE step > 0",
    "merge_steps_heap": f"{tree_of(SYM4, 3, 4, stop=8)} SELECT step::INT AS step, (leaves + step - 1)::INT AS node, a::INT AS \"left\", b::INT AS \"right\", round(d + 0.0, 6) AS delta, round(sum(d) OVER (ORDER BY step) + 0.0, 6) AS loss FROM tr_steps WHERE step > 0",
    "w1_binning_text42": binning(SYM42, 1, 42),
    "w2_binning_class4_order3": binning(SYM4, 3, 4),
    "w1_loss_curve": f"""{tree_of(SYM42, 1, 42)}, curve AS (SELECT len(live) AS bins, (SELECT sum(own) FROM tr_leaf) / (SELECT t FROM tr_t) + sum(d) OVER (ORDER BY step) AS bpv FROM tr_steps),
      low AS (SELECT i.i AS drop, (41 >> i.i::INT) + 1 AS bins, ctx >> i.i::INT AS ctx, sym, sum(n) AS n FROM cnt, range(1, 5) i(i) GROUP BY ALL), lw AS (SELECT bins AS b2, bpv AS low FROM ({rate_of('low', 'bins')}))
      SELECT bins::INT AS bins, round(bpv, 6) AS bpv, low AS low_bits_bpv FROM curve LEFT JOIN lw ON b2 = bins""",
    "flagship": f"""{tree_of(SYM42, 1, 42)}, {within_loss('bn', 'tr', 0.01)}, alt AS (SELECT 'none' AS method, ctx, 0 AS bin FROM tr_leaf UNION ALL SELECT 'binned', ctx, bin FROM bn UNION ALL SELECT 'complete', ctx, node FROM tr_leaf),
      cl AS (SELECT method, bin AS ctx, sym, sum(n) AS n FROM alt JOIN cnt USING (ctx) GROUP BY ALL) {rate_of('cl', 'method')}""",
    "cuts_class4_order3": f"""{tree_of(SYM4, 3, 4)}, {within_loss('c1', 'tr', 0.01)}, {at_bins('c2', 'tr', 6)},
      top AS (SELECT step, sum((d < 0.001)::INT) OVER (ORDER BY step DESC) AS low FROM tr_steps WHERE step > 0), keep AS (SELECT (SELECT max(step) FROM tr_steps) - count(*) AS step FROM top WHERE low = 0),
      {numbered('c3', 'SELECT g, live FROM tr_steps WHERE step = (SELECT step FROM keep)')},
      nodes AS (SELECT node, lo, ctxs, a, b, d FROM (SELECT node, node AS lo, [ctx] AS ctxs, NULL::BIGINT AS a, NULL::BIGINT AS b, NULL::DOUBLE AS d FROM tr_leaf
        UNION ALL SELECT x.node, x.lo, x.leaf, a, b, d FROM (SELECT live[len(live)] AS x, a, b, d FROM tr_steps WHERE step > 0))),
      fr AS (SELECT [max(node)] AS f FROM nodes UNION ALL SELECT list_concat(list_filter(f, lambda x: x <> o.node), [o.a, o.b]) FROM (
        SELECT f, (SELECT max({{'d': n.d, 'node': n.node, 'a': n.a, 'b': n.b}}) FROM nodes n WHERE list_contains(fr.f, n.node) AND n.a IS NOT NULL) AS o FROM fr WHERE len(f) < 6) WHERE o IS NOT NULL),
      c4 AS (SELECT unnest(ctxs) AS ctx, row_number() OVER (ORDER BY lo) - 1 AS bin FROM nodes WHERE list_contains((SELECT arg_max(f, len(f)) FROM fr), node))
      SELECT rule, ctx, bin::INT AS bin FROM (SELECT 'loss' AS rule, ctx, bin FROM c1 UNION ALL SELECT 'bins', ctx, bin FROM c2 UNION ALL SELECT 'gain', ctx, bin FROM c3 UNION ALL SELECT 'bins, largest gain', ctx, bin FROM c4)""",
    "cut_levels_text42": f"{tree_of(SYM42, 1, 42)}, {at_bins('b2', 'tr', 2)}, {at_bins('b8', 'tr', 8)}, {at_bins('b16', 'tr', 16)} SELECT bins::INT AS bins, ctx, bin::INT AS bin FROM (SELECT 2 AS bins, ctx, bin FROM b2 UNION ALL SELECT 8, ctx, bin FROM b8 UNION ALL SELECT 16, ctx, bin FROM b16)",
    "two_level_bins": f"""{tree_of(SYM42, 1, 42)}, {at_bins('fine', 'tr', 32)}, fc AS (SELECT bin AS ctx, sym, sum(n) AS n FROM fine JOIN cnt USING (ctx) GROUP BY ALL), {grown('sc', 'fc', 42, stop=4, capacity=8)},
      {numbered('gr', 'SELECT g, arg_max(live, step) AS live FROM sc_steps GROUP BY g')}, pl AS (SELECT ctx AS f, bin * 8 + row_number() OVER (PARTITION BY bin ORDER BY ctx) - 1 AS place FROM gr)
      SELECT ctx, place::INT AS bin, (place >> 3)::INT AS coarse FROM fine JOIN pl ON f = bin""",
    "trees_by_language": f"""WITH RECURSIVE {SYM4}, {before(2, 4)}, ln AS (SELECT lang, ctx, s AS sym, count(*) AS n FROM win JOIN documents ON doc_id = k GROUP BY ALL), {grown('tr', 'ln', 4, by='lang')}, {at_bins('bn', 'tr', 4)} SELECT g AS lang, ctx, bin::INT AS bin FROM bn""",
    "best_partitions_ev5": f"""WITH RECURSIVE {EV5}, {before(1, 5)}, {COUNTS}, tot AS (SELECT sum(n) AS t FROM cnt), lab AS (SELECT 0 AS i, []::BIGINT[] AS l, 0 AS used UNION ALL SELECT i + 1, list_append(l, x.x), greatest(used, x.x + 1) FROM lab, range(5) x(x) WHERE i < 5 AND x.x <= used),
      parts AS (SELECT row_number() OVER (ORDER BY l) AS p, l, used FROM lab WHERE i = 5), cl AS (SELECT p, used, l[ctx + 1] AS bin, sym, sum(n) AS n FROM parts, cnt GROUP BY ALL),
      rt AS (SELECT p, used, sum(n * log2(n) - g) / (SELECT t FROM tot) AS bpv FROM (SELECT p, used, bin, sum(n) AS n, sum(n * log2(n)) AS g FROM cl GROUP BY ALL) GROUP BY ALL)
      SELECT k.k::INT AS bins, round(min(bpv) + 0.0, 6) AS bpv FROM rt, range(1, 6) k(k) WHERE used <= k.k GROUP BY k.k""",
}


def overfit(win: str, m: int, alpha: float, fold: str = "k % 2", by: str = "") -> str:
    """n, training, held_out of windows (by, k, ctx, s)."""
    comma, group = (f"{by}, ", f" GROUP BY {by}") if by else ("", "")
    return f"""SELECT {comma}sum(n0 + n1)::BIGINT AS n, round(sum((n0 + n1) * log2((t0 + t1) / (n0 + n1))) / sum(n0 + n1) + 0.0, 6) AS training,
        round(sum(n0 * log2((t1 + {alpha * m}) / (n1 + {alpha})) + n1 * log2((t0 + {alpha * m}) / (n0 + {alpha}))) / sum(n0 + n1), 6) AS held_out
      FROM (SELECT *, sum(n0) OVER (PARTITION BY {comma}ctx) AS t0, sum(n1) OVER (PARTITION BY {comma}ctx) AS t1
        FROM (SELECT {comma}ctx, s, count(*) FILTER ({fold} = 0) AS n0, count(*) FILTER ({fold} = 1) AS n1 FROM {win} GROUP BY ALL)){group}"""


def null_controls() -> str:
    parts, ctes = [], []
    for name, source, m in (("ev5", EV5, 5), ("val42", VAL42, 42), ("qty50", QTY50, 50), ("wordlen16", WORDLEN, 16), ("text42", SYM42, 42)):
        ctes.append(f"{name}_x AS (WITH {source} SELECT k, s, lag(s) OVER (PARTITION BY k ORDER BY pos) AS ctx, 0 AS none FROM sym), {name}_w AS (SELECT * FROM {name}_x WHERE ctx IS NOT NULL), {name}_z AS (SELECT k, s, 0 AS ctx FROM {name}_w)")
        parts.append(f"SELECT '{name}' AS stream, b.n, a.training AS none_training, a.held_out AS none_held_out, b.training AS order1_training, b.held_out AS order1_held_out FROM ({overfit(f'{name}_z', m, 1.0)}) a, ({overfit(f'{name}_w', m, 1.0)}) b")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def page_positions() -> str:
    """Positions, previous values and the hand-made context on first reads and on all reads of pages."""
    ctes, parts = [], []
    for name, reads in (("all", f"WITH {PAGES42} SELECT k, r, pos, s FROM rd"), ("first read only", f"WITH {PAGE42} SELECT k, 0 AS r, pos, s FROM sym")):
        x = "a" if name == "all" else "f"
        ctes.append(f"""{x}0 AS ({reads}), {x}1 AS (SELECT *, lag(s) OVER w AS p1, lag(s, 2) OVER w AS p2 FROM {x}0 WINDOW w AS (PARTITION BY k, r ORDER BY pos)),
          {x}2 AS (SELECT *, coalesce(sum((p1 <> s)::INT) OVER (PARTITION BY k, r ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ch FROM {x}1)""")
        for context, size, code, start in (
            ("none", 1, "0", 1), ("position", 101, "pos", 1), ("previous", 42, "p1", 1), ("both", 101 * 42, "pos + 101 * p1", 1),
            ("handmade", 121 * 32, "(p1 >> 2) + 11 * (p2 >> 2) + 121 * least(pos // 16, 7) + 968 * least(ch // 8, 3)", 2),
        ):
            w = f"{x}_{context}"
            ctes.append(f"{w} AS (SELECT k, s, {code} AS ctx FROM {x}2 WHERE pos >= {start})")
            parts.append(f"SELECT '{name}' AS reads, '{context}' AS context, {size} AS contexts, * FROM ({overfit(w, 42, 0.1)})")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def position_bins() -> str:
    ctes, parts = [], []
    for name, x, reads in (("all", "a", f"WITH {PAGES42} SELECT pos AS ctx, s AS sym, count(*) AS n FROM rd GROUP BY ALL"), ("first read only", "f", f"WITH {PAGE42} SELECT pos AS ctx, s AS sym, count(*) AS n FROM sym GROUP BY ALL")):
        ctes.append(f"{x}c AS ({reads}), {grown(x, f'{x}c', 42)}, {within_loss(f'{x}b', x, 0.01)}, {x}i AS (SELECT *, (bin IS DISTINCT FROM lag(bin) OVER (ORDER BY ctx))::INT AS new FROM {x}b)")
        parts.append(f"SELECT '{name}' AS reads, bin::INT AS bin, min(ctx) AS first, max(ctx) AS last, count(*) AS members, sum(new)::BIGINT AS runs FROM {x}i GROUP BY bin")
    return f"WITH RECURSIVE {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def joint(rows: str, a: str, b: str, name: str) -> str:
    return f"""SELECT '{name}' AS pair, n, round(ha, 6) AS h_a, round(hb, 6) AS h_b, round(hab, 6) AS h_ab, round(ha + hb - hab, 6) AS gain
      FROM (SELECT sum(n)::BIGINT AS n, log2(sum(n)) - sum(n * log2(na)) / sum(n) AS ha, log2(sum(n)) - sum(n * log2(nb)) / sum(n) AS hb, log2(sum(n)) - sum(n * log2(n)) / sum(n) AS hab
        FROM (SELECT n, sum(n) OVER (PARTITION BY a) AS na, sum(n) OVER (PARTITION BY b) AS nb FROM (SELECT {a} AS a, {b} AS b, count(*) AS n FROM {rows} GROUP BY ALL)))"""


def chain(x: str, m: int, sizes: list[int], one_tree: bool, windows: str = "lw") -> tuple[str, str, int]:
    """CTEs that bin the value at each distance, the packed code of the bins, and the number of states. ``windows`` has p1, p2 ... and s."""
    ctes, tables, code, base = [], [], [], 1
    if one_tree:
        ctes.append(f"{x}c AS (SELECT p1 AS ctx, s AS sym, count(*) AS n FROM {windows} WHERE p1 IS NOT NULL GROUP BY ALL), {grown(x, f'{x}c', m)}")
        for j, size in enumerate(sizes, 1):
            ctes.append(at_bins(f"{x}b{j}", x, size))
    else:
        for j, size in enumerate(sizes, 1):
            inner = f"p{j}" if j == 1 else "bin"
            join = "" if j == 1 else f" JOIN {x}b{j - 1} ON ctx0 = ctx"
            raw = f"SELECT p{j} AS ctx0, s AS sym, count(*) AS n FROM {windows} WHERE p{j} IS NOT NULL GROUP BY ALL"
            inner = "ctx0" if j == 1 else "bin"
            ctes.append(f"{x}r{j} AS ({raw}), {x}c{j} AS (SELECT {inner} AS ctx, sym, sum(n) AS n FROM {x}r{j}{join} GROUP BY ALL), {grown(f'{x}t{j}', f'{x}c{j}', m, stop=size)}, {at_bins(f'{x}l{j}', f'{x}t{j}', size)}")
            # value -> its bin at this level
            ctes.append(f"{x}b{j} AS (SELECT ctx, bin FROM {x}l{j})" if j == 1 else f"{x}b{j} AS (SELECT b.ctx, l.bin FROM {x}b{j - 1} b JOIN {x}l{j} l ON l.ctx = b.bin)")
    for j, size in enumerate(sizes, 1):
        tables.append(f"JOIN {x}b{j} t{j} ON t{j}.ctx = p{j}")
        code.append(f"t{j}.bin * {base}")
        base *= size
    ctes.append(f"{x}w AS (SELECT {' + '.join(code)} AS ctx, s AS sym, count(*) AS n FROM {windows} {' '.join(tables)} GROUP BY ALL)")
    return ", ".join(ctes), f"{x}w", base


def packed_windows() -> str:
    lags = ", ".join(f"lag(s, {i}) OVER w AS p{i}" for i in range(1, 9))
    ctes, parts = [f"lw AS (SELECT s, {lags} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos))"], []
    for x, name, sizes, one in (("ca", "16-4-2-2", [16, 4, 2, 2], False), ("cb", "16-4-2-2 one tree", [16, 4, 2, 2], True), ("cc", "8-8-4", [8, 8, 4], False), ("cd", "2^8", [2] * 8, False)):
        cte, cells, states = chain(x, 42, sizes, one)
        ctes.append(cte)
        parts.append(f"SELECT '{name}' AS machine, {states} AS states, n, bpv FROM ({rate_of(cells)})")
    return f"WITH RECURSIVE {SYM42}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def counters() -> str:
    """Machines by window functions: last value, changes, run length, two chained bins, and the bins with changes."""
    outer, totals = [], []
    for stream, source, m, x in (("class4", READS4, 4, "wi"), ("wordlen16", f"{WORDLEN}, rd AS (SELECT k, 0 AS r, pos, s FROM sym)", 16, "wl")):
        ctes, _, _ = chain(x, m, [4, 2], False, f"{x}lr")
        parts = []
        for name, code in (
            ("none", "0"), ("last value", "p"), ("changes", f"least(ch, 15) * {m} + p"), ("run length", f"least(rl - 1, 3) * {m} + p"),
            ("window", "a.bin + 4 * b.bin"), ("window x changes", f"a.bin + 4 * b.bin + 8 * (least(ch, 7) * {m} + p)"),
        ):
            parts.append(f"SELECT '{name}' AS machine, {code} AS ctx, s AS sym, count(*) AS n FROM {x}q JOIN {x}b1 a ON a.ctx = p1 JOIN {x}b2 b ON b.ctx = p2 WHERE pos >= 2 GROUP BY ALL")
        outer.append(f"""{x}rd AS (WITH {source} SELECT k, r, pos, s FROM rd), {x}lr AS (SELECT *, lag(s) OVER w AS p1, lag(s, 2) OVER w AS p2 FROM {x}rd WINDOW w AS (PARTITION BY k, r ORDER BY pos)), {ctes},
          {x}q0 AS (SELECT *, coalesce(p1, 0) AS p, (s IS DISTINCT FROM coalesce(p1, 0))::INT AS f FROM {x}lr),
          {x}q1 AS (SELECT *, sum(f) OVER (PARTITION BY k, r ORDER BY pos) AS run, coalesce(sum(f) OVER (PARTITION BY k, r ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ch FROM {x}q0),
          {x}q2 AS (SELECT *, row_number() OVER (PARTITION BY k, r, run ORDER BY pos) + (run = 0)::INT AS len FROM {x}q1), {x}q AS (SELECT *, lag(len, 1, 1) OVER (PARTITION BY k, r ORDER BY pos) AS rl FROM {x}q2),
          {x}cl AS ({' UNION ALL '.join(parts)})""")
        totals.append(f"SELECT '{stream}' AS stream, machine, n, contexts AS states, bpv FROM ({rate_of(f'{x}cl', 'machine')})")
    return f"WITH RECURSIVE {', '.join(outer)} {' UNION ALL '.join(totals)}"


def position_controls() -> str:
    ctes, parts = [], []
    sources = (
        ("emb16", "e", f"WITH {EMB16} SELECT k, pos, s FROM sym", 33), ("first reads, text42", "t", f"WITH {SYM42} SELECT k, pos, s FROM sym WHERE pos < 101 AND k IN (SELECT doc_id FROM documents WHERE length(text) >= 101)", 42),
        ("first reads, class4", "c", f"WITH {SYM4} SELECT k, pos, s FROM sym WHERE pos < 101 AND k IN (SELECT doc_id FROM documents WHERE length(text) >= 101)", 4),
    )
    for name, x, source, m in sources:
        for context, code in (("none", "0"), ("position", "pos")):
            w = f"{x}_{context}"
            ctes.append(f"{w} AS (SELECT k, s, {code} AS ctx FROM ({source}))")
            parts.append(f"SELECT '{name}' AS stream, '{context}' AS context, * FROM ({overfit(w, m, 0.1)})")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(parts)}"



ORACLES |= {
    "w17_null_controls": null_controls(),
    "w3_position_previous": page_positions(),
    "w3_position_bins": position_bins(),
    "position_rates_pages": f"""WITH {PAGES42}, x AS (SELECT *, lag(s) OVER (PARTITION BY k, r ORDER BY pos) AS p FROM rd),
      cl AS (SELECT 'position' AS context, pos AS ctx, s AS sym, count(*) AS n FROM x GROUP BY ALL UNION ALL SELECT 'position, previous', pos + 101 * p, s, count(*) FROM x WHERE pos >= 1 GROUP BY ALL UNION ALL SELECT 'coarse position', least(pos // 10, 7), s, count(*) FROM x GROUP BY ALL) {rate_of('cl', 'context')}""",
    "w14_joint_gain": f"{joint('events', EV, VAL, 'event type, value')} UNION ALL {joint('lineitem', 'l_returnflag', 'l_linestatus', 'return flag, line status')}",
    "w16_read_order": "SELECT n AS reads, round(lgamma(n + 1) / ln(2), 3) AS order_bits, round(lgamma(n + 1) / ln(2) / greatest(n, 1), 6) AS bits_per_read FROM (SELECT sum((length(text) + 100) // 101)::BIGINT AS n FROM documents)",
    "w3_position_controls": position_controls(),
    "w5_packed_windows": packed_windows(),
    "w6_counters": counters(),
}


def kmeans(x: str, k: int, m: int, contexts: int, alpha: float, rounds: int, tol: float, init: str = "spread", update: str = "joint", drop: bool = False, keys: tuple[str, ...] = ("k", "r"), names: tuple[str, ...] = ("k", "r"), seed: int = 0) -> str:
    """CTEs of k-means over reads: <x>_a (keys, c, bits, n): the last assignment, and <x>_h (rounds). Expects cells rc (keys, ctx, sym, n) and
    rl (keys, n, syms). Rounds are unrolled; the first whose total changes by at most ``tol`` is the last."""
    key = ", ".join(keys)
    grid = f"range({contexts}) a(i), range({m}) b(i)"
    ctes = []

    def models(out: str, pool: str, live: str) -> None:
        ctes.append(f"{out} AS (SELECT c, ctx, sym, log2(sum(n) OVER (PARTITION BY c, ctx) / n) AS bits FROM (SELECT g.c, g.ctx, g.sym, coalesce(p.n, 0) + {alpha} AS n FROM (SELECT c.c, a.i AS ctx, b.i AS sym FROM ({live}) c, {grid}) g LEFT JOIN {pool} p ON p.c = g.c AND p.ctx = g.ctx AND p.sym = g.sym))")

    order = f"{draw(list(names), seed)}, {key}" if init != "first" else key
    ctes.append(f"{x}_seed AS (SELECT {key}, row_number() OVER (ORDER BY {order}) - 1 AS c FROM rl WHERE len(syms) > 0 QUALIFY c < {1 if init == 'spread' else k})")
    cells = lambda chosen: f"SELECT c, ctx, sym, n::DOUBLE AS n FROM rc JOIN ({chosen}) USING ({key})"
    if init == "spread":
        ctes.append(f"{x}_p0 AS ({cells(f'SELECT {key}, c FROM {x}_seed')})")
        for j in range(1, k):
            models(f"{x}_s{j}", f"{x}_p{j - 1}", f"SELECT i.i AS c FROM range({j}) i(i)")
            ctes.append(f"{x}_u{j} AS (SELECT {key}, round(min(b) / any_value(n), 9) AS c FROM (SELECT {key}, c, sum(n * bits) AS b FROM rc JOIN {x}_s{j} USING (ctx, sym) GROUP BY ALL) JOIN (SELECT {key}, n FROM rl) USING ({key}) GROUP BY {key})")
            ctes.append(f"{x}_v{j} AS (SELECT arg_max(f, {{'c': c, 's': syms}}) AS f FROM (SELECT {{{', '.join(f'{q!r}: {q}' for q in keys)}}} AS f, u.c, syms FROM {x}_u{j} u JOIN rl USING ({key})))")
            ctes.append(f"{x}_p{j} AS (SELECT * FROM {x}_p{j - 1} UNION ALL {cells(f'SELECT {', '.join(f'f.{q} AS {q}' for q in keys)}, {j} AS c FROM {x}_v{j}')})")
        pool = f"{x}_p{k - 1}"
    else:
        ctes.append(f"{x}_p0 AS ({cells(f'SELECT {key}, c FROM {x}_seed')})")
        pool = f"{x}_p0"
    live = f"SELECT i.i AS c FROM range({k}) i(i)"
    totals = []
    for i in range(rounds + 1):
        models(f"{x}_m{i}", pool, live)
        ctes.append(f"{x}_a{i} AS (SELECT {key}, (min({{'b': b, 'c': c}})).c AS c, min(b) AS bits FROM (SELECT {key}, c, round(sum(n * bits), 9) AS b FROM rc JOIN {x}_m{i} USING (ctx, sym) GROUP BY ALL) GROUP BY {key})")
        weight = "n" if update == "joint" else "n * w"
        source = "rc" if update == "joint" else f"(SELECT rc.*, l.n / sum(rc.n) OVER (PARTITION BY {', '.join(f'rc.{q}' for q in keys)}, ctx) AS w FROM rc JOIN (SELECT {key}, sum(n) AS n FROM rc GROUP BY {key}) l USING ({key}))"
        ctes.append(f"{x}_q{i} AS (SELECT c, ctx, sym, sum({weight})::DOUBLE AS n FROM {source} JOIN {x}_a{i} USING ({key}) GROUP BY ALL)")
        totals.append(f"SELECT {i} AS i, sum(bits) AS t FROM {x}_a{i}")
        pool = f"{x}_q{i}"
        if drop:
            live = f"SELECT DISTINCT c FROM {x}_a{i}"
    stop = f"abs(lag(t) OVER (ORDER BY i) - t) <= {tol} * greatest(abs(t), 1e-12)"
    ctes.append(f"{x}_t AS ({' UNION ALL '.join(totals[:-1])}), {x}_h AS (SELECT least(coalesce(min(i) FILTER (stop), {rounds}) + 1, {rounds}) AS rounds FROM (SELECT i, {stop} AS stop FROM {x}_t))")
    last = " UNION ALL ".join(f"SELECT * FROM {x}_a{i} WHERE {i} = (SELECT rounds FROM {x}_h)" for i in range(1, rounds + 1))
    pools = " UNION ALL ".join(f"SELECT * FROM {x}_m{i} WHERE {i} = (SELECT rounds FROM {x}_h)" for i in range(1, rounds + 1))
    # reads without counted symbols go to the first model
    ctes.append(f"{x}_a AS (SELECT {key}, coalesce(c, 0) AS c, coalesce(bits, 0) AS bits, n FROM (SELECT {key}, n FROM rl) LEFT JOIN ({last}) USING ({key})), {x}_m AS ({pools})")
    return ", ".join(ctes)


def read_cells(source: str, order: int = 1, m: int = 4) -> str:
    """rc and rl of the reads rd (k, r, pos, s) under contexts of the previous values; n counts the symbols with a context."""
    lags = "".join(f", lag(s, {i}) OVER w AS p{i}" for i in range(1, order + 1))
    code = " + ".join(f"p{i} * {m ** (i - 1)}" for i in range(1, order + 1))
    return f"""{source}, rw AS (SELECT k, r, pos, s, {code} AS ctx FROM (SELECT *{lags} FROM rd WINDOW w AS (PARTITION BY k, r ORDER BY pos)) WHERE pos >= {order}),
      rc AS (SELECT k, r, ctx, s AS sym, count(*) AS n FROM rw GROUP BY ALL), rl AS (SELECT k, r, greatest(count(*) - {order}, 0) AS n, list(s ORDER BY pos) AS syms FROM rd GROUP BY k, r)"""


def purity(assigned: str, label: str) -> str:
    return f"(SELECT round(sum(top) / sum(n), 6) FROM (SELECT max(n) AS top, sum(n) AS n FROM (SELECT c, {label}, count(*) AS n FROM {assigned} GROUP BY ALL) GROUP BY c))"


def clusters(cells: str, m: int, contexts: int, label: str, labels: str, sizes: tuple[int, ...] = (1, 2, 4, 8)) -> str:
    ctes, parts = [], []
    for k in sizes:
        x = f"k{k}"
        ctes.append(kmeans(x, k, m, contexts, 0.1, 8, 1e-3))
        ctes.append(f"{x}_l AS (SELECT a.*, {label} AS lab FROM {x}_a a {labels})")
        ctes.append(f"{x}_c AS (SELECT lab AS l, sum(count(*)) OVER w AS b, sum(count(*)) OVER () AS t FROM {x}_l GROUP BY lab WINDOW w AS (ORDER BY lab NULLS FIRST ROWS UNBOUNDED PRECEDING))")
        ctes.append(f"{x}_s AS (SELECT k, r, c, (SELECT list(l ORDER BY b)[1] FROM {x}_c q WHERE q.b > floor({draw(['k', 'r'])} * q.t)) AS lab FROM {x}_l)")
        parts.append(f"""SELECT {k} AS k, count(*) AS reads, round(sum(bits) / sum(n), 6) AS model_bpv, round(count(*) * log2({k}) / sum(n), 6) AS flat_bpv,
          (SELECT round((sum(v) * log2(sum(v)) - sum(v * log2(v))) / sum(s) + 0.0, 6) FROM (SELECT count(*) AS v, sum(n) AS s FROM {x}_l GROUP BY c)) AS entropy_bpv,
          round((sum(bits) + count(*) * log2({k})) / sum(n), 6) AS total_bpv, {purity(f'{x}_l', 'lab')} AS purity, {purity(f'{x}_s', 'lab')} AS chance, (SELECT rounds FROM {x}_h)::INT AS rounds FROM {x}_l""")
    return f"WITH {cells}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def class_switching() -> str:
    """Header, mixture by forgotten bits, best so far, one model."""
    step = lambda mix: (
        "-log2(list_sum(list_transform(list_zip(past, cost), lambda z: pow(2, list_min(past) - z[1]) * pow(2, -z[2]))) / list_sum(list_transform(past, lambda z: pow(2, list_min(past) - z))))"
        if mix else "cost[list_position(past, list_min(past))]"
    )
    walk = lambda x, mix: f"""{x} AS (SELECT k, r, 0::BIGINT AS i, [0.0, 0.0, 0.0, 0.0]::DOUBLE[] AS past, 0.0::DOUBLE AS spent FROM rl WHERE len(syms) > 0
      UNION ALL SELECT {x}.k, {x}.r, o.pos, list_transform(list_zip(past, cost), lambda z: 0.95::DOUBLE * z[1] + z[2]), spent + {step(mix)} FROM {x} JOIN o ON o.k = {x}.k AND o.r = {x}.r AND o.pos = {x}.i + 1)"""  # noqa: E731
    total = lambda x: f"(SELECT round(sum(s) / (SELECT sum(n) FROM rl), 6) FROM (SELECT max_by(spent, i) AS s FROM {x} GROUP BY k, r))"
    return f"""WITH RECURSIVE {read_cells(READS4)}, {kmeans('k4', 4, 4, 4, 0.1, 5, 1e-4)}, {kmeans('k1', 1, 4, 4, 0.1, 2, 1e-4, init='random')},
      lists AS (SELECT ctx, sym, list(bits ORDER BY c) AS cost FROM k4_m GROUP BY ctx, sym), o AS (SELECT k, r, pos, cost FROM rw JOIN lists ON lists.ctx = rw.ctx AND lists.sym = rw.s), {walk('wm', True)}, {walk('wb', False)}
      SELECT 'header' AS method, (SELECT round((sum(bits) + 2 * count(*)) / sum(n), 6) FROM k4_a) AS bpv UNION ALL SELECT 'mixture', {total('wm')} UNION ALL SELECT 'best so far', {total('wb')}
      UNION ALL SELECT 'one model', (SELECT round(sum(bits) / sum(n), 6) FROM k1_a)"""


def user_variants() -> str:
    """Users' events clustered in several ways."""
    users = f"{EV5}, rd AS (SELECT k, 0 AS r, pos, s FROM sym)"
    ctes, parts = [], []
    for x, name, options in (
        ("vr", "random", {"init": "random"}), ("vs", "spread", {"init": "spread"}), ("vf", "first", {"init": "first"}),
        ("vc", "conditional", {"init": "first", "update": "conditional"}), ("vd", "drop", {"init": "random", "drop": True}), ("v2", "seed 1", {"init": "random", "seed": 1}),
    ):
        ctes.append(kmeans(x, 3, 5, 5, 0.5, 3, -1, **options))
        parts.append(f"SELECT '{name}' AS variant, c::INT AS cluster, count(*) AS reads, round(sum(bits), 4) AS bits FROM {x}_a GROUP BY c")
    # the better of two starts, by the total of the last round before the final assignment
    best = "(SELECT t FROM vr_t WHERE i = 2) <= (SELECT t FROM v2_t WHERE i = 2)"
    parts.append(f"SELECT 'restarts', c::INT, count(*), round(sum(bits), 4) FROM (SELECT * FROM vr_a WHERE {best} UNION ALL SELECT * FROM v2_a WHERE NOT {best}) GROUP BY c")
    return f"WITH {read_cells(users, 1, 5)}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


EMB_CELLS = f"{EMB16}, rc AS (SELECT k, 0 AS r, pos AS ctx, s AS sym, count(*) AS n FROM sym GROUP BY ALL), rl AS (SELECT k, 0 AS r, count(*) AS n, list(s ORDER BY pos) AS syms FROM sym GROUP BY k)"
_LABELS = "LEFT JOIN (SELECT doc_id, quality FROM labels) ON doc_id = k"
ORACLES |= {
    "w8_clusters_text42": clusters(read_cells(READS42, 1, 42), 42, 42, "lang", "LEFT JOIN (SELECT doc_id, lang FROM documents) ON doc_id = k"),
    "w9_clusters_class4": clusters(read_cells(READS4, 1, 4), 4, 4, "quality", _LABELS),
    "w9_position_clusters": clusters(EMB_CELLS, 33, 64, "label", "LEFT JOIN (SELECT vec_id, label FROM embeddings) ON vec_id = k", (10,)),
    "cluster_histogram": f"WITH {read_cells(READS42, 1, 42)}, {kmeans('h', 4, 42, 42, 0.1, 5, 1e-4)} SELECT c::INT AS cluster, round(floor(bits / n / 0.1) * 0.1, 6) AS bucket, count(*) AS reads FROM h_a WHERE n > 0 GROUP BY 1, 2",
    "selector_context": f"""WITH {read_cells(READS4)}, {kmeans('h', 4, 4, 4, 0.1, 5, 1e-4)}, one AS (SELECT ctx, sym, sum(n) AS n FROM rc GROUP BY ALL), large AS (SELECT ctx + 4 * c AS ctx, sym, sum(n) AS n FROM rc JOIN (SELECT k, r, c FROM h_a) USING (k, r) GROUP BY ALL)
      SELECT 'one' AS models, contexts, bpv FROM ({rate_of('one')}) UNION ALL SELECT 'selector', contexts, bpv FROM ({rate_of('large')}) UNION ALL SELECT 'four', 16, (SELECT round(sum(bits) / sum(n), 6) FROM h_a)""",
    "soft_switching": class_switching(),
    "cluster_variants_ev5": user_variants(),
}


def adaptive_reads(x: str, order: int, every: int = 1, rate: int = 8, source: str = "rd", m: int = 4) -> str:
    """CTE <x> (k, r, bits, n): every read by itself under integer functions per context of the previous values."""
    top, key = 1 << 15, "k, r"
    lags = "".join(f", lag(s, {i}) OVER w AS p{i}" for i in range(1, order + 1))
    code = " + ".join(f"p{i} * {m ** (i - 1)}" for i in range(1, order + 1)) or "0"
    uniform = "[" + ", ".join(str((j << 15) // m) for j in range(m + 1)) + "]::BIGINT[]"
    ctes = [f"{x}o AS (SELECT {key}, pos, s, {code} AS c FROM (SELECT *{lags} FROM {source} WINDOW w AS (PARTITION BY {key} ORDER BY pos)) WHERE pos >= {order})"]
    ctes.append(f"{x}i AS (SELECT *, (row_number() OVER (PARTITION BY {key}, c ORDER BY pos) - 1) // {every} AS i FROM {x}o)")
    # the symbols of a step, and where they draw the function: to one symbol's, or to the step's own distribution
    if every == 1:
        target = f"list_transform(range({m + 1}), lambda j: CASE WHEN j <= any_value(s) THEN j ELSE {top - m} + j END)"
    else:
        target = f"list_transform(range({m + 1}), lambda j: j + ({top - m} * list_sum(list_concat([0], list_transform(list(s), lambda v: (v < j)::INT)))::BIGINT) // {every})"
    ctes.append(f"{x}g AS (SELECT {key}, c, i, list(s) AS ss, count(*) AS n, {target} AS t FROM {x}i GROUP BY {key}, c, i)")
    cost = "list_sum(list_transform(g.ss, lambda v: 15 - log2((f.cdf[v + 2] - f.cdf[v + 1])::DOUBLE)))"
    ctes.append(f"""{x}f AS (SELECT {key}, c, -1::BIGINT AS i, {uniform} AS cdf, 0.0::DOUBLE AS bits, 0::BIGINT AS n FROM (SELECT DISTINCT {key}, c FROM {x}g)
      UNION ALL SELECT f.k, f.r, f.c, g.i, CASE WHEN g.n = {every} THEN list_transform(list_zip(f.cdf, g.t), lambda z: z[1] + ((z[2] - z[1]) >> {rate})) ELSE f.cdf END, f.bits + {cost}, f.n + g.n
      FROM {x}f f JOIN {x}g g ON g.k = f.k AND g.r = f.r AND g.c = f.c AND g.i = f.i + 1)""")
    ctes.append(f"{x} AS (SELECT {key}, sum(bits) AS bits, sum(n)::BIGINT AS n FROM (SELECT {key}, c, max_by(bits, i) AS bits, max(n) AS n FROM {x}f GROUP BY {key}, c) GROUP BY {key})")
    return ", ".join(ctes)


def adaptive_orders() -> str:
    ctes, parts = [], []
    for order in range(4):
        x = f"ad{order}"
        ctes.append(adaptive_reads(x, order))
        ctes.append(f"{x}c AS (SELECT c AS ctx, s AS sym, count(*) AS n FROM {x}o GROUP BY ALL)")
        parts.append(f"SELECT {order} AS ord, sum(n)::BIGINT AS n, round(sum(bits) / sum(n), 6) AS adaptive, (SELECT bpv FROM ({rate_of(f'{x}c')})) AS static FROM {x}")
    return f"WITH RECURSIVE {READS4}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def sparse_updates() -> str:
    ctes, parts = [], []
    for every, rate in ((1, 8), (10, 5), (25, 2)):
        ctes.append(adaptive_reads(f"sp{every}", 1, every, rate))
        parts.append(f"SELECT {every} AS every, {rate} AS rate, sum(n)::BIGINT AS n, round(sum(bits) / sum(n), 6) AS bpv FROM sp{every}")
    return f"WITH RECURSIVE {READS4}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


ETAS = (0.8, 0.9, 0.95, 0.98, 0.99, 0.995)
FREQUENCY_FLOOR = 1e-6


def fitted_rates() -> str:
    """The forgetting rate of a grid under which each user's events cost least."""
    m, floor = 5, FREQUENCY_FLOOR
    shifted = "list_transform(range(1, 6), lambda j: v[j] * eta + CASE WHEN j = o.s + 1 THEN 1 - eta ELSE 0 END)"
    return f"""WITH RECURSIVE {EV5}, o AS (SELECT k, pos, s FROM sym), e AS (SELECT unnest([{', '.join(map(str, ETAS))}])::DOUBLE AS eta),
      f AS (SELECT k, eta, -1::BIGINT AS i, [0.2, 0.2, 0.2, 0.2, 0.2]::DOUBLE[] AS v, 0.0::DOUBLE AS bits FROM (SELECT DISTINCT k FROM o), e
        UNION ALL SELECT f.k, eta, o.pos, {shifted}, bits - log2((1 - {m} * {floor}::DOUBLE) * v[o.s + 1] + {floor}::DOUBLE) FROM f JOIN o ON o.k = f.k AND o.pos = f.i + 1),
      z AS (SELECT k, eta, max(i) + 1 AS n, round(max_by(bits, i), 6) AS bits FROM f GROUP BY k, eta)
      SELECT k AS block_no, n, eta, round(-1 / log2(eta), 6) AS half_life, round(bits / n, 6) AS bpv FROM z QUALIFY row_number() OVER (PARTITION BY k ORDER BY bits, eta) = 1"""


def soft_objective() -> str:
    """Sum of state-weighted log emissions, and of logs of the mixture, of a declared two-state machine."""
    return f"""WITH RECURSIVE {EV5}, o AS (SELECT k, pos, s FROM sym), T AS (SELECT x.x AS x, a.a AS a, (1 + x.x) / (7.0 + a.a) AS p0 FROM range(5) x(x), range(2) a(a)),
      D AS (SELECT x, (x + 1) / 15.0::DOUBLE AS e0, (5 - x) / 15.0::DOUBLE AS e1 FROM (SELECT x.x AS x FROM range(5) x(x))),
      f AS (SELECT k, -1::BIGINT AS i, 1.0::DOUBLE AS q0, 0.0::DOUBLE AS q1, 0.0::DOUBLE AS nats, 0.0::DOUBLE AS mix FROM (SELECT DISTINCT k FROM o)
        UNION ALL SELECT f.k, o.pos, q0 * t0.p0 + q1 * t1.p0, q0 * (1 - t0.p0) + q1 * (1 - t1.p0), nats + q0 * ln(e0) + q1 * ln(e1), mix - log2(q0 * e0 + q1 * e1)
        FROM f JOIN o ON o.k = f.k AND o.pos = f.i + 1 JOIN T t0 ON t0.x = o.s AND t0.a = 0 JOIN T t1 ON t1.x = o.s AND t1.a = 1 JOIN D ON D.x = o.s),
      z AS (SELECT max_by(nats, i) AS nats, max_by(mix, i) AS mix FROM f GROUP BY k) SELECT round(sum(nats), 4) AS objective, round(sum(mix), 4) AS mixture_bits FROM z"""


def nestings() -> str:
    """Nested binnings of the class stream over windows from place 4 on."""
    lags = ", ".join(f"lag(s, {i}) OVER w AS p{i}" for i in range(1, 5))
    base = f"{SYM4}, lw AS (SELECT k, pos, s, {lags} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos))"
    count = lambda x, code, where, join="": f"{x}c AS (SELECT {code} AS ctx, s AS sym, count(*) AS n FROM lw {join} WHERE {where} GROUP BY ALL)"
    near, far = "p1 + 4 * p2", "p3 + 4 * p4"
    ctes = [base]
    for bins in (6, 3):
        ctes += [count(f"pr{bins}", near, "pos >= 2"), grown(f"pr{bins}", f"pr{bins}c", 4), at_bins(f"pr{bins}b", f"pr{bins}", bins)]
    # symmetric: the pair table again, two places earlier; far values exist from place 4 on
    ctes += [count("sy", "a.bin + 6 * b.bin", "pos >= 4", f"JOIN pr6b a ON a.ctx = {near} JOIN pr6b b ON b.ctx = {far}"), grown("sy", "syc", 4), at_bins("syb", "sy", 12)]
    # asymmetric: the far pair by how it predicts the symbol
    ctes += [count("fa", far, "pos >= 4"), grown("fa", "fac", 4), at_bins("fab", "fa", 3)]
    # far bins as near bins without their last bit: near bins paired by how they predict from two places earlier
    ctes += [count("ff", "b.bin", "pos >= 4", f"JOIN pr6b b ON b.ctx = {far}"), grown("ff", "ffc", 4, stop=6), at_bins("ffi", "ff", 6),
             grown("fs", "ffc", 4, stop=3, capacity=2), numbered("fsg", "SELECT g, arg_max(live, step) AS live FROM fs_steps GROUP BY g"),
             "ffb AS (SELECT ctx, bin AS grp, bin * 2 + row_number() OVER (PARTITION BY bin ORDER BY ctx) - 1 AS place FROM fsg)"]
    # hierarchical: a tree of the far pair inside every near bin
    ctes += [f"hic AS (SELECT a.bin AS near, {far} AS ctx, s AS sym, count(*) AS n FROM lw JOIN pr3b a ON a.ctx = {near} WHERE pos >= 4 GROUP BY ALL)", grown("hi", "hic", 4, by="near"), at_bins("hib", "hi", 2)]
    # with another context: previous value and the place in words of four
    ctes += [count("wi", "p1 + 4 * least(pos // 4, 3)", "pos >= 1"), grown("wi", "wic", 4), at_bins("wib", "wi", 5)]
    n = f"JOIN pr6b a ON a.ctx = {near}"
    final = [
        ("pair", 6, 1, "a.bin", n), ("symmetric", 12, 2, "y.bin", f"{n} JOIN pr6b b ON b.ctx = {far} JOIN syb y ON y.ctx = a.bin + 6 * b.bin"),
        ("asymmetric", 18, 2, "a.bin + 6 * f.bin", f"{n} JOIN fab f ON f.ctx = {far}"),
        ("far_from_near", "6 * (SELECT (max(place) >> 1) + 1 FROM ffb)", 1, "x.place + 1000 * y.grp", f"{n} JOIN pr6b b ON b.ctx = {far} JOIN ffb x ON x.ctx = a.bin JOIN ffb y ON y.ctx = b.bin"),
        ("hierarchical", "(SELECT count(*) FROM (SELECT DISTINCT g, bin FROM hib))", 2, "a.bin * 1000 + h.bin", f"JOIN pr3b a ON a.ctx = {near} JOIN hib h ON h.g = a.bin AND h.ctx = {far}"),
        ("with", 5, 1, "w.bin", "JOIN wib w ON w.ctx = p1 + 4 * least(pos // 4, 3)"), ("complete", 256, 4, f"{near} + 16 * ({far})", ""),
    ]
    parts = []
    for kind, states, lookups, code, join in final:
        x = "z_" + kind
        ctes.append(f"{x} AS (SELECT {code} AS ctx, s AS sym, count(*) AS n FROM lw {join} WHERE pos >= 4 GROUP BY ALL)")
        parts.append(f"SELECT '{kind}' AS kind, ({states})::INT AS states, {lookups} AS lookups, n, bpv FROM ({rate_of(x)})")
    return f"WITH RECURSIVE {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def prefix_codes() -> str:
    """Total of the merged weights of a prefix code per context: lightest two first."""
    return f"""WITH RECURSIVE {SYM42}, {before(1, 42)}, {COUNTS}, h AS (SELECT ctx, list_sort(list(n::BIGINT)) AS w, CASE WHEN count(*) = 1 THEN sum(n) ELSE 0 END::BIGINT AS cost FROM cnt GROUP BY ctx
        UNION ALL SELECT ctx, list_sort(list_append(w[3:], w[1] + w[2])), cost + w[1] + w[2] FROM h WHERE len(w) > 1),
      z AS (SELECT ctx, max(cost) AS cost FROM h GROUP BY ctx), i AS (SELECT sum(n * log2(t / n)) AS ideal, sum(n)::BIGINT AS n FROM (SELECT n, sum(n) OVER (PARTITION BY ctx) AS t FROM cnt))
      SELECT n, round((SELECT sum(cost) FROM z) / n, 6) AS prefix_bpv, round(ideal / n + 0.0, 6) AS ideal_bpv FROM i"""


def plain_codes() -> str:
    """Order 0, raw, prefix, run lengths and block sorting of the class reads."""
    return f"""WITH RECURSIVE {READS4}, c0 AS (SELECT 0 AS ctx, s AS sym, count(*) AS n FROM rd GROUP BY ALL), tot AS (SELECT sum(n)::BIGINT AS n FROM c0),
      h AS (SELECT list_sort(list(n::BIGINT)) AS w, 0::BIGINT AS cost FROM c0 UNION ALL SELECT list_sort(list_append(w[3:], w[1] + w[2])), cost + w[1] + w[2] FROM h WHERE len(w) > 1),
      f AS (SELECT *, (s IS DISTINCT FROM lag(s) OVER (PARTITION BY k, r ORDER BY pos))::INT AS new FROM rd), g AS (SELECT k, r, s, sum(new) OVER (PARTITION BY k, r ORDER BY pos) AS run FROM f),
      q AS (SELECT s, len, count(*) AS n FROM (SELECT k, r, run, any_value(s) AS s, count(*) AS len FROM g GROUP BY k, r, run) GROUP BY s, len),
      t AS (SELECT k, r, string_agg(s::VARCHAR, '' ORDER BY pos) AS x FROM rd GROUP BY k, r), ro AS (SELECT k, r, i, substr(x || x, i + 1, length(x)) AS y, substr(x || x, i + length(x), 1)::INT AS last FROM (SELECT k, r, x, unnest(range(length(x))) AS i FROM t)),
      bw AS (SELECT last AS s, coalesce(lag(last) OVER (PARTITION BY k, r ORDER BY y, i), 4) AS ctx FROM ro), bc AS (SELECT ctx, s AS sym, count(*) AS n FROM bw GROUP BY ALL)
      SELECT 'order 0' AS method, n, bpv FROM ({rate_of('c0')}) UNION ALL SELECT 'raw', n, 2.0 FROM tot UNION ALL SELECT 'prefix code', n, round((SELECT max(cost) FROM h) / n, 6) FROM tot
      UNION ALL SELECT 'run lengths', sum(n * len)::BIGINT, round((sum(n) * log2(sum(n)) - sum(n * log2(n))) / sum(n * len) + 0.0, 6) FROM q UNION ALL SELECT 'block sorting, order 1', n, bpv FROM ({rate_of('bc')})"""


def integer_frequencies() -> str:
    parts = []
    for b in (8, 10, 12, 14):
        room = (1 << b) - 42
        parts.append(f"""SELECT {b} AS bits, round(sum(CASE WHEN p > 0 THEN t * p * log2(p / (q / {1 << b})) ELSE 0 END) / sum(CASE WHEN sym = 0 THEN t ELSE 0 END), 6) AS loss_bpv FROM (
          SELECT *, floor(p * {room}) + 1 + (row_number() OVER (PARTITION BY ctx ORDER BY floor(p * {room}) - p * {room}, sym) <= {room} - sum(floor(p * {room})) OVER (PARTITION BY ctx))::INT AS q FROM pr)""")
    return f"""WITH {SYM42}, {before(1, 42)}, {COUNTS}, pr AS (SELECT c.ctx, i.i AS sym, t, coalesce(n, 0) / t AS p FROM (SELECT ctx, sum(n)::DOUBLE AS t FROM cnt GROUP BY ctx) c CROSS JOIN range(42) i(i) LEFT JOIN cnt ON cnt.ctx = c.ctx AND cnt.sym = i.i) {' UNION ALL '.join(parts)}"""


ORACLES |= {
    "adaptive_orders_reads": adaptive_orders(),
    "sparse_updates_reads": sparse_updates(),
    "fitted_rates_users": fitted_rates(),
    "soft_objective_ev5": soft_objective(),
    "nestings_class4": nestings(),
    "prefix_rate_text42": prefix_codes(),
    "baseline_codes": plain_codes(),
    "integer_loss": integer_frequencies(),
    "decoded_reads": f"WITH {READS4} SELECT k AS doc_id, r::INT AS read_no, count(*)::INT AS n, md5(string_agg(s::VARCHAR, '' ORDER BY pos)) AS digest FROM rd GROUP BY k, r",
    "contingency_langs": f"""WITH {READS4}, rw AS (SELECT k, r, s, lag(s) OVER (PARTITION BY k, r ORDER BY pos) AS ctx FROM rd), rc AS (SELECT k, r, ctx, s AS sym, count(*) AS n FROM rw WHERE ctx IS NOT NULL GROUP BY ALL),
      lc AS (SELECT lang, ctx, sym, sum(n) AS n FROM rc JOIN documents ON doc_id = k GROUP BY ALL), lg AS (SELECT lang, row_number() OVER (ORDER BY lang) - 1 AS c FROM (SELECT DISTINCT lang FROM lc)),
      md AS (SELECT c, a.i AS ctx, b.i AS sym, coalesce(lc.n, 0) + 0.5 AS n FROM lg CROSS JOIN range(4) a(i) CROSS JOIN range(4) b(i) LEFT JOIN lc ON lc.lang = lg.lang AND lc.ctx = a.i AND lc.sym = b.i),
      mb AS (SELECT c, ctx, sym, log2(sum(n) OVER (PARTITION BY c, ctx) / n) AS bits FROM md), t AS (SELECT k, r, c, round(sum(n * bits), 9) AS b FROM rc JOIN mb USING (ctx, sym) GROUP BY ALL), best AS (SELECT k, r, min({{'b': b, 'c': c}}) AS x FROM t GROUP BY ALL)
      SELECT x.c::INT AS cluster, lang AS label, count(*) AS reads FROM best JOIN documents ON doc_id = k GROUP BY 1, 2""",
    "read_file_rates": f"""WITH a AS (WITH {READS42} SELECT k, r, pos, s AS q FROM rd), b AS (WITH {READS4} SELECT k, r, pos, s AS b FROM rd), x AS (SELECT k, r, pos, q, b, lag(q) OVER w AS pq, lag(b) OVER w AS pb FROM a JOIN b USING (k, r, pos) WINDOW w AS (PARTITION BY k, r ORDER BY pos)),
      cl AS (SELECT 'quality' AS symbols, pq AS ctx, q AS sym, count(*) AS n FROM x WHERE pos >= 1 GROUP BY ALL UNION ALL SELECT 'bases', pb, b, count(*) FROM x WHERE pos >= 1 GROUP BY ALL UNION ALL SELECT 'packed', (pq << 2) | pb, (q << 2) | b, count(*) FROM x WHERE pos >= 1 GROUP BY ALL) {rate_of('cl', 'symbols')}""",
    "decoded_adaptive": f"WITH {EV5} SELECT k AS user_id, md5(string_agg(s::VARCHAR, '' ORDER BY pos)) AS digest FROM sym GROUP BY k",
    "position_symbol_rate": f"WITH {SYM4}, x AS (SELECT *, lag(s) OVER (PARTITION BY k ORDER BY pos) AS p FROM sym), cl AS (SELECT p + 4 * least((pos - 1) // 16, 7) AS ctx, s AS sym, count(*) AS n FROM x WHERE pos >= 1 GROUP BY ALL) {rate_of('cl')}",
    "long_machines": f"""WITH {SYM4}, a AS (SELECT row_number() OVER (ORDER BY k, pos) - 1 AS i, s FROM sym), b AS (SELECT i, s, lag(s) OVER w AS p1, lag(s, 2) OVER w AS p2 FROM a WINDOW w AS (ORDER BY i)),
      f AS (SELECT *, (s IS DISTINCT FROM coalesce(p1, 0))::INT AS f FROM b), g AS (SELECT *, sum(f) OVER (ORDER BY i) AS run FROM f), h AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY i) + (run = 0)::INT AS len FROM g),
      j AS (SELECT *, lag(len, 1, 1) OVER (ORDER BY i) AS rl FROM h),
      cl AS (SELECT 'window' AS machine, p1 + 4 * (p2 >= 2)::INT AS ctx, s AS sym, count(*) AS n FROM j WHERE i >= 2 GROUP BY ALL UNION ALL SELECT 'run length', least(rl - 1, 3) * 4 + p1, s, count(*) FROM j WHERE i >= 2 GROUP BY ALL) {rate_of('cl', 'machine')}""",
    "consensus_of_hosts": f"""WITH {PAGE42}, h AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS g FROM pages), x AS (SELECT g, k, pos, s FROM sym JOIN h ON page_id = k),
      co AS (SELECT g, pos, (max({{'n': n, 'neg': -s}})).neg * -1 AS ref FROM (SELECT g, pos, s, count(*) AS n FROM x GROUP BY ALL) GROUP BY g, pos), d AS (SELECT s, (s <> ref)::INT AS miss FROM x JOIN co USING (g, pos)),
      p AS (SELECT miss, s, count(*) AS n FROM d GROUP BY ALL), q AS (SELECT miss, sum(n) AS k, sum(n * log2(n)) AS g FROM p GROUP BY miss)
      SELECT n, round(fb / n + 0.0, 6) AS flag_bpv, round(sb / n + 0.0, 6) AS replacement_bpv, round((fb + sb) / n + 0.0, 6) AS bpv FROM (SELECT sum(k)::BIGINT AS n, sum(k) * log2(sum(k)) - sum(k * log2(k)) AS fb, sum(CASE WHEN miss = 1 THEN k * log2(k) - g ELSE 0 END) AS sb FROM q)""",
    "entropy_headers": f"""WITH {READS4}, rw AS (SELECT k, r, s, lag(s) OVER (PARTITION BY k, r ORDER BY pos) AS ctx FROM rd), rc AS (SELECT k, r, ctx, s AS sym, count(*) AS n FROM rw WHERE ctx IS NOT NULL GROUP BY ALL),
      lc AS (SELECT lang, ctx, sym, sum(n) AS n FROM rc JOIN documents ON doc_id = k GROUP BY ALL), lg AS (SELECT lang, row_number() OVER (ORDER BY lang) - 1 AS c, (SELECT sum(n) FROM lc x WHERE x.lang = l.lang) AS w FROM (SELECT DISTINCT lang FROM lc) l),
      md AS (SELECT c, w, a.i AS ctx, b.i AS sym, coalesce(lc.n, 0) + 0.5 AS n FROM lg CROSS JOIN range(4) a(i) CROSS JOIN range(4) b(i) LEFT JOIN lc ON lc.lang = lg.lang AND lc.ctx = a.i AND lc.sym = b.i),
      mb AS (SELECT c, ctx, sym, log2(sum(n) OVER (PARTITION BY c, ctx) / n) AS bits FROM md), hd AS (SELECT c, -log2(w / sum(w) OVER ()) AS h FROM lg),
      t AS (SELECT k, r, c, round(sum(n * bits) + any_value(h), 9) AS b FROM rc JOIN mb USING (ctx, sym) JOIN hd USING (c) GROUP BY ALL), best AS (SELECT k, r, min({{'b': b, 'c': c}}) AS x FROM t GROUP BY ALL)
      SELECT x.c::INT AS cluster, count(*) AS reads, round(sum(x.b), 4) AS bits FROM best GROUP BY 1""",
    "model_sizes": f"""WITH {SYM4}, l AS (SELECT s, pos, {', '.join(f'lag(s, {i}) OVER w AS p{i}' for i in range(1, 4))} FROM sym WINDOW w AS (PARTITION BY k ORDER BY pos)),
      cl AS (SELECT 0 AS ord, 0 AS ctx, s AS sym, count(*) AS n FROM l GROUP BY ALL UNION ALL SELECT 1, p1, s, count(*) FROM l WHERE pos >= 1 GROUP BY ALL UNION ALL SELECT 2, p1 + 4 * p2, s, count(*) FROM l WHERE pos >= 2 GROUP BY ALL UNION ALL SELECT 3, p1 + 4 * p2 + 16 * p3, s, count(*) FROM l WHERE pos >= 3 GROUP BY ALL)
      SELECT ord, pow(4, ord)::INT AS contexts, pow(4, ord + 1)::INT AS cells, pow(4, ord + 1)::INT * 2 AS bytes, round(2 / bpv, 6) AS ratio FROM ({rate_of('cl', 'ord')})""",
}
