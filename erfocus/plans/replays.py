"""Chains, alias tables and parallel rounds as recursive DuckDB SQL, written apart from the kernel.

Relations that the texts expect: mem (component, mention_id), the members; qs (component, query_id, own), the
queries; pw (component, i, j, w) with i < j, the weights; wts0 (query_id, mention_id, weight), what draws are
weighted by.  Places are positions of a component's members by id, from 1; an entity is named by its smallest place.
"""

from __future__ import annotations

from erfocus.functions.rand import sql_h32

SPAN = "4294967296"


def h(text: str) -> str:
    return sql_h32(text, "duckdb")


def places() -> str:
    """Members by place, rows of weights, draws' weights by place."""
    return """lst AS (SELECT component, list(mention_id ORDER BY mention_id) AS ids, count(*) AS n FROM mem GROUP BY 1),
pos AS (SELECT component, mention_id, row_number() OVER (PARTITION BY component ORDER BY mention_id) AS p FROM mem),
both_ways AS (SELECT component, i, j, w FROM pw WHERE i <> j UNION ALL SELECT component, j, i, w FROM pw WHERE i <> j),
cell AS (SELECT a.component, a.p AS p, b.p AS r, coalesce(e.w, 0) AS w FROM pos a JOIN pos b USING (component) LEFT JOIN both_ways e ON e.component = a.component AND e.i = a.mention_id AND e.j = b.mention_id),
mrow AS MATERIALIZED (SELECT component, p, list(w ORDER BY r) AS ws FROM cell GROUP BY 1, 2),
wts AS (SELECT component, query_id, p, coalesce(weight, 0)::DOUBLE AS w FROM qs JOIN pos USING (component) LEFT JOIN wts0 USING (query_id, mention_id))"""


def cumulated() -> str:
    """Integer cumulative weights of each query."""
    return """cumw AS (SELECT component, query_id, p, (sum(floor(w * 1000000 + 0.5)::BIGINT) OVER (PARTITION BY component, query_id ORDER BY p))::BIGINT AS c FROM wts),
drawn AS (SELECT component, query_id, list(c ORDER BY p) AS cum, [1.0::DOUBLE] AS pr, [1::BIGINT] AS al FROM cumw GROUP BY 1, 2)"""


def aliased(source: str = "wts") -> str:
    """Alias tables of each query, by pairing the last place that has too little with the last that has too much."""
    put = lambda xs, at, value: f"list_transform({xs}, lambda x, i: CASE WHEN i = {at} THEN {value} ELSE x END)"
    return f"""vin AS (SELECT component, query_id, list(w ORDER BY p) AS ws, sum(w) AS total, count(*) AS n FROM {source} GROUP BY 1, 2),
vsc AS (SELECT component, query_id, n, list_transform(ws, lambda x: x * (n / total)) AS sc FROM vin),
vose AS (
SELECT component, query_id, sc, list_filter(range(1, n + 1), lambda i: sc[i] < 1) AS sm, list_filter(range(1, n + 1), lambda i: sc[i] >= 1) AS lg,
  list_transform(sc, lambda x: 1.0::DOUBLE) AS pr, range(1, n + 1) AS al FROM vsc
UNION ALL SELECT component, query_id, {put('sc', 'g', 'v')}, CASE WHEN v < 1 THEN list_append(sm[1:len(sm) - 1], g) ELSE sm[1:len(sm) - 1] END, CASE WHEN v < 1 THEN lg[1:len(lg) - 1] ELSE lg END,
  {put('pr', 's', 'sc[s]')}, {put('al', 's', 'g')}
  FROM (SELECT *, sc[g] - (1 - sc[s]) AS v FROM (SELECT *, sm[len(sm)] AS s, lg[len(lg)] AS g FROM vose WHERE len(sm) > 0 AND len(lg) > 0))),
tables AS (SELECT component, query_id, pr, al FROM vose WHERE len(sm) = 0 OR len(lg) = 0)"""


def turns(total: int, quantum: int) -> str:
    """(component, turn): for each step the number of the query whose turn it is, by selectivity."""
    return f"""sl AS (SELECT component, query_id, count(*) AS sel FROM qs JOIN infl USING (query_id) GROUP BY 1, 2),
t0 AS (SELECT *, {total} * sel / sum(sel) OVER (PARTITION BY component) AS x FROM sl),
t1 AS (SELECT *, floor(x)::BIGINT AS b, {total} - sum(floor(x)::BIGINT) OVER (PARTITION BY component) AS lft, row_number() OVER (PARTITION BY component ORDER BY round(x - floor(x), 9) DESC, query_id) AS r FROM t0),
t2 AS (SELECT component, query_id, (b + CASE WHEN r <= lft THEN 1 ELSE 0 END)::BIGINT AS k, row_number() OVER (PARTITION BY component ORDER BY sel DESC, query_id) AS big, row_number() OVER (PARTITION BY component ORDER BY query_id) AS qi FROM t1),
t3 AS (SELECT *, unnest(range(0, k, {quantum})) AS a FROM t2),
t4 AS (SELECT component, qi, least({quantum}, k - a) AS size, (a // {quantum}) / ceil(k / {quantum}) AS due, big, a FROM t3),
t5 AS (SELECT component, list(qi ORDER BY due, big, a) AS qis, list(size ORDER BY due, big, a) AS sizes FROM t4 GROUP BY 1),
planned AS (SELECT component, flatten(list_transform(qis, lambda q, i: list_transform(range(0, sizes[i]), lambda z: q))) AS turn FROM t5)"""


HOLDING = ("pin_target", "influence_to_query", "expel", "expel_both")


def chain(
    sampler: str, steps: int, tau: float = 0.9, runs: int = 1, quantum: int = 500, draw: str = "cdf", policy: str = "round_robin", temperature: float | None = None, single: bool | None = None, seed: int = 1, idle: int | None = None, start: str | None = None
) -> str:
    """Relations up to ch (component, run, t, qi, src, dst, mv, delta, ok, lab, nxt): a row a proposal, and one before the first.

    temperature: Metropolis-Hastings acceptance, of uniform and influence_to_query.  start: a relation (component,
    lab) of places' entities to set out from.
    """
    u = lambda slot: h(f"'{seed}|' || run || '|' || t || '|{slot}'")
    pick = lambda options, slot: f"{options}[1 + ({u(slot)} * len({options}) >> 32)]"

    def drawn(slot: int) -> str:
        if draw == "cdf":
            return f"1 + len(list_filter(cum, lambda z: z * {SPAN} <= {u(slot)} * cum[len(cum)]))"
        at = f"least(floor({u(slot)} / {SPAN}.0 * n)::BIGINT, n - 1) + 1"
        return f"CASE WHEN {u(slot + 1)} / {SPAN}.0 < pr[{at}] THEN {at} ELSE al[{at}] END"

    ent = "list_sort(list_distinct(lab))"
    without = lambda x: f"list_filter(ent, lambda z: z <> {x})"
    of = lambda x: f"list_filter(range(1, n + 1), lambda z: lab[z] = {x})"
    guided = f"{u(0)} < {int(tau * (1 << 32))}"
    any_target = "list_append(ent, 0)" if temperature is not None else "ent"
    parts = [f"{ent} AS ent"]
    if sampler == "uniform":
        parts += [f"{pick('ent', 1)} AS src, {pick(any_target, 3)} AS dst", f"{pick(of('src'), 2)} AS mv"]
    elif sampler == "pin_target":
        parts += [f"{guided} AS g", f"CASE WHEN g THEN eq ELSE {pick(f'list_append({without("eq")}, 0)', 3)} END AS dst", f"{pick(without('dst'), 1)} AS src", f"{pick(of('src'), 2)} AS mv"]
    elif sampler == "influence_both":
        parts += [f"{drawn(5)} AS mv, lab[{drawn(7)}] AS dst", "lab[mv] AS src"]
    elif sampler == "influence_to_query":
        tries = "[" + ", ".join(drawn(s) for s in (5, 9, 11, 13, 15)) + "]"
        parts += [
            f"{guided} AS g, {tries} AS tries",
            "coalesce(list_filter(tries, lambda z: lab[z] <> eq)[1], tries[5]) AS hit",
            f"CASE WHEN g THEN lab[hit] ELSE {pick('ent', 1)} END AS src, CASE WHEN g THEN eq ELSE {pick(any_target, 3)} END AS dst",
            f"CASE WHEN g THEN hit ELSE {pick(of('src'), 2)} END AS mv",
        ]
    else:
        other = f", lab[{drawn(7)}] AS other" if sampler == "expel_both" else ""
        away = "CASE WHEN other = eq THEN 0 ELSE other END" if sampler == "expel_both" else pick(f"list_append({without('eq')}, 0)", 3)
        parts += [
            f"{guided} AS g, {drawn(5)} AS hit{other}",
            f"CASE WHEN g THEN {away} ELSE {pick('list_append(ent, 0)', 3)} END AS dst",
            f"CASE WHEN g THEN lab[hit] ELSE {pick(without('dst'), 1)} END AS src",
            f"CASE WHEN g THEN hit ELSE {pick(of('src'), 2)} END AS mv",
        ]
    turn = "turn[t + 2]" if policy == "by_selectivity" else f"((t + 1) // {quantum}) % len(qids) + 1"
    going = f" AND NOT (vain >= {idle} AND (t + 1) % 100 = 0)" if idle else ""
    body = f"SELECT ch.component, run, t + 1 AS t, vain, nxt AS lab, con.* EXCLUDE (component), {turn} AS qi FROM ch JOIN con USING (component) WHERE t + 1 < {steps}{going}"
    body = f"SELECT *, lab[ats[qi]] AS eq, cums[qi] AS cum, prs[qi] AS pr, als[qi] AS al FROM ({body})"
    for add in parts:
        body = f"SELECT *, {add} FROM ({body})"
    held = "list_contains(ats, mv) OR " if sampler in HOLDING else ""
    body = f"SELECT *, {of('src')} AS leaving FROM ({body})"
    body = f"SELECT *, (mv IS NULL OR src IS NULL OR dst IS NULL OR {held}src = dst OR (dst = 0 AND len(leaving) = 1)) AS noop FROM ({body})"
    body = f"SELECT x.*, r.ws FROM ({body}) x LEFT JOIN mrow r ON r.component = x.component AND r.p = x.mv"
    total = lambda x: f"coalesce(list_sum(list_transform(lab, lambda y, z: CASE WHEN y = {x} THEN ws[z] ELSE 0 END)), 0)"
    body = f"SELECT *, CASE WHEN noop THEN 0 ELSE {total('dst')} - {total('src')} END AS delta, CASE WHEN src = mv THEN leaving[2] ELSE src END AS nsrc, CASE WHEN dst = 0 THEN mv ELSE least(dst, mv) END AS ndst FROM ({body})"
    moved = "list_transform(lab, lambda y, z: CASE WHEN z = mv THEN ndst WHEN y = src THEN nsrc WHEN y = dst THEN ndst ELSE y END)"
    if temperature is None:
        body = f"SELECT *, delta > 0 AS ok FROM ({body})"
        body = f"SELECT *, CASE WHEN ok THEN {moved} ELSE lab END AS nxt FROM ({body})"
    else:
        share = lambda labels, e: f"list_sum(list_transform({labels}, lambda y, z: CASE WHEN y = {e} THEN sh[z] ELSE 0 END))"
        body = f"SELECT *, CASE WHEN noop THEN lab ELSE {moved} END AS then_, list_transform(cum, lambda c, z: (c - CASE WHEN z > 1 THEN cum[z - 1] ELSE 0 END) / cum[len(cum)]) AS sh FROM ({body})"
        body = f"SELECT *, len(ent) AS ne, len(list_distinct(then_)) AS ne2, len(leaving) AS k, len(list_filter(then_, lambda z: z = then_[mv])) AS k2, then_[ats[qi]] AS eq2 FROM ({body})"
        uniform, uniform2 = "1 / ne / k / (ne + 1)", "1 / ne2 / k2 / (ne2 + 1)"
        if sampler == "influence_to_query":
            to = lambda labels, e, when: f"CASE WHEN {when} THEN sh[mv] / greatest(1 - {share(labels, e)}, 1e-300) ELSE 0 END"
            uniform = f"{tau} * {to('lab', 'eq', 'dst = eq')} + (1 - {tau}) * {uniform}"
            uniform2 = f"{tau} * {to('then_', 'eq2', 'src = eq')} + (1 - {tau}) * {uniform2}"
        body = f"SELECT *, delta / {temperature} + ln({uniform2}) - ln({uniform}) AS ratio FROM ({body})"
        body = f"SELECT *, NOT noop AND (ratio >= 0 OR ln(greatest({u(4)} / {SPAN}.0, 1e-300)) < ratio) AS ok FROM ({body})"
        body = f"SELECT *, CASE WHEN ok THEN then_ ELSE lab END AS nxt FROM ({body})"
    body = f"SELECT * EXCLUDE (vain), CASE WHEN ok THEN 0 ELSE vain + 1 END AS vain FROM ({body})"
    columns = "component, run, t, vain, qi, src, dst, mv, delta, ok, lab, nxt"
    whole = sampler in ("expel", "expel_both") if single is None else single
    first = f"start.lab" if start else "list_transform(range(1, n + 1), lambda z: 1::BIGINT)" if whole else "range(1, n + 1)"
    plan = f"{turns(steps, quantum)},\n" if policy == "by_selectivity" else ""
    return f"""{cumulated() if draw == "cdf" else aliased() + ", drawn AS (SELECT component, query_id, [1::BIGINT] AS cum, pr, al FROM tables)"},
{plan}ql AS (SELECT component, list(query_id ORDER BY query_id) AS qids, list(p ORDER BY query_id) AS ats, list(cum ORDER BY query_id) AS cums, list(pr ORDER BY query_id) AS prs, list(al ORDER BY query_id) AS als
       FROM qs JOIN pos USING (component) JOIN drawn USING (component, query_id) WHERE pos.mention_id = qs.own GROUP BY 1),
con AS MATERIALIZED (SELECT lst.component, n, ids, qids, ats, cums, prs, als{", turn" if plan else ""} FROM lst JOIN ql USING (component){" JOIN planned USING (component)" if plan else ""}),
ch AS (
SELECT component, run, (-1)::BIGINT AS t, 0::BIGINT AS vain, 1::BIGINT AS qi, NULL::BIGINT AS src, NULL::BIGINT AS dst, NULL::BIGINT AS mv, 0::HUGEINT AS delta, false AS ok, {first} AS lab, {first} AS nxt
FROM con{" JOIN " + start + " start USING (component)" if start else ""}, range(0, {runs}) AS r(run)
UNION ALL SELECT {columns} FROM ({body}))"""


def members_of_queries(step: int) -> str:
    """(component, run, query_id, mention_id): the members of queries' entities after a step, their own left out."""
    return f"""SELECT component, run, qids[k] AS query_id, ids[z] AS mention_id FROM (SELECT ch.*, con.ids, con.qids, con.ats, con.n, unnest(range(1, len(qids) + 1)) AS k FROM ch JOIN con USING (component) WHERE t = {step}) x,
range(1, (SELECT max(n) FROM con) + 1) AS r(z) WHERE z <= n AND nxt[z] = nxt[ats[k]] AND z <> ats[k]"""


def accuracy() -> str:
    """f (component, run, t, qi, tp, m, f1q): each query's accuracy after each step; gold: (mention_id, gold), of members."""
    return """gl AS (SELECT component, list(gold ORDER BY mention_id) AS golds FROM mem JOIN gold USING (mention_id) GROUP BY 1),
f0 AS (SELECT ch.component, run, t, k AS qi, list_filter(range(1, n + 1), lambda z: nxt[z] = nxt[ats[k]] AND z <> ats[k]) AS own, golds, golds[ats[k]] AS g FROM ch JOIN con USING (component) JOIN gl USING (component), range(1, (SELECT max(len(qids)) FROM con) + 1) AS r(k) WHERE k <= len(qids)),
f1 AS (SELECT component, run, t, qi, len(list_filter(own, lambda z: golds[z] = g)) AS tp, len(own) AS m, len(list_filter(golds, lambda x: x = g)) - 1 AS rel FROM f0),
f AS (SELECT component, run, t, qi, tp, m, CASE WHEN tp > 0 THEN 2 * (tp / m) * (tp / rel) / (tp / m + tp / rel) ELSE 0.0 END AS f1q FROM f1)"""


def rounds(n: int, workers: int, watch: str, seed: int = 1) -> str:
    """Relations st0 to st<n> (mention_id, entity_id): states after parallel rounds, with the fall-back to uniform proposals.

    Expects tabs (query_id, ids, pr, al), st0, both_ways (i, j, w), and the watchlist's own mentions.
    """
    out = []
    for k in range(n):
        hh = lambda slot, text, k=k: h(f"'{seed}|{k}|{slot}|' || {text}")
        first = lambda src: f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY e ORDER BY pr, query_id, n) AS r FROM {src}) WHERE r = 1"  # noqa: E731, B023
        claims = lambda src: f"(SELECT entity_from AS e, pr, query_id, n FROM {src} UNION ALL SELECT entity_to, pr, query_id, n FROM {src})"
        won = lambda src, cl: f"SELECT x.* FROM {src} x JOIN {cl} a ON a.e = x.entity_from AND a.query_id = x.query_id AND a.n = x.n JOIN {cl} b ON b.e = x.entity_to AND b.query_id = x.query_id AND b.n = x.n"
        out.append(f"""{proposals(k, workers, watch, f"st{k}", seed)},
pp{k} AS MATERIALIZED (SELECT *, {hh('p', "query_id || '|' || n")} AS pr FROM pr{k}),
cl{k} AS ({first(claims(f'pp{k}'))}), wn{k} AS MATERIALIZED ({won(f'pp{k}', f'cl{k}')}),
lo{k} AS (SELECT query_id, n, row_number() OVER (ORDER BY query_id, n) AS k FROM pp{k} p WHERE NOT EXISTS (SELECT 1 FROM wn{k} w WHERE w.query_id = p.query_id AND w.n = p.n)),
fr{k} AS (SELECT * FROM st{k} WHERE entity_id NOT IN (SELECT entity_from FROM wn{k} UNION ALL SELECT entity_to FROM wn{k})),
en{k} AS (SELECT entity_id, arg_min(mention_id, {hh('bm', 'mention_id')}) AS mention_id FROM fr{k} GROUP BY 1),
bs{k} AS (SELECT entity_id, mention_id, row_number() OVER (ORDER BY {hh('bs', 'entity_id')}, entity_id) AS k FROM en{k}),
bt{k} AS (SELECT entity_id, row_number() OVER (ORDER BY {hh('bt', 'entity_id')}, entity_id) AS k FROM en{k}),
bp{k} AS MATERIALIZED (SELECT query_id, n, s.mention_id, s.entity_id AS entity_from, t.entity_id AS entity_to, {hh('p', "query_id || '|' || n")} AS pr FROM lo{k} JOIN bs{k} s USING (k) JOIN bt{k} t USING (k)
  WHERE s.entity_id <> t.entity_id AND s.mention_id NOT IN (SELECT query_id FROM {watch})),
bc{k} AS ({first(claims(f'bp{k}'))}), bw{k} AS MATERIALIZED ({won(f'bp{k}', f'bc{k}')}),
mv{k} AS (SELECT mention_id, entity_from, entity_to FROM wn{k} UNION ALL SELECT mention_id, entity_from, entity_to FROM bw{k}),
{better(f'mv{k}', f'st{k}', f'gd{k}')},
{applied(f'gd{k}', f'st{k}', f'st{k + 1}')}""")
    return ",\n".join(out)


def proposals(k: int, workers: int, watch: str, state: str, seed: int = 1) -> str:
    """pr<k> (query_id, n, mention_id, entity_from, entity_to): workers' draws in a round."""
    hh = lambda slot, text: h(f"'{seed}|{k}|{slot}|' || {text}")
    return f"""sq{k} AS (SELECT query_id, row_number() OVER (ORDER BY query_id) - 1 AS place, count(*) OVER () AS many FROM {watch}),
as{k} AS (SELECT query_id, n FROM range(1, {workers + 1}) AS r(n) JOIN sq{k} ON place = {hh('q', 'n')} * many >> 32),
{drawn_mentions(k, f'as{k}', state, watch, seed)}"""


def drawn_mentions(k: int, asked: str, state: str, watch: str, seed: int = 1) -> str:
    """pr<k> from (query_id, n): influence draws by alias tables to queries' entities."""
    hh = lambda slot: h(f"'{seed}|{k}|{slot}|' || query_id || '|' || n")
    at = f"least(floor({hh('a')} / {SPAN}.0 * len(ids))::BIGINT, len(ids) - 1) + 1"
    return f"""dr{k} AS (SELECT query_id, n, ids[CASE WHEN {hh('b')} / {SPAN}.0 < pr[{at}] THEN {at} ELSE al[{at}] END] AS mention_id FROM {asked} JOIN tabs USING (query_id)),
pr{k} AS (SELECT d.query_id, d.n, d.mention_id, s.entity_id AS entity_from, o.entity_id AS entity_to FROM dr{k} d JOIN {state} s ON s.mention_id = d.mention_id JOIN {state} o ON o.mention_id = d.query_id
  WHERE s.entity_id <> o.entity_id AND d.mention_id NOT IN (SELECT query_id FROM {watch}))"""


def better(moves: str, state: str, name: str) -> str:
    """The moves of positive delta."""
    return f"""{name}d AS (SELECT m.mention_id, m.entity_to, sum(CASE WHEN s.entity_id = m.entity_to THEN b.w WHEN s.entity_id = m.entity_from THEN -b.w ELSE 0 END) AS delta FROM {moves} m JOIN both_ways b ON b.i = m.mention_id JOIN {state} s ON s.mention_id = b.j GROUP BY ALL),
{name} AS MATERIALIZED (SELECT mention_id, entity_to, delta FROM {name}d WHERE delta > 0)"""


def applied(moves: str, state: str, name: str) -> str:
    """The state after moves, entities named by their smallest mention."""
    return f"{name} AS MATERIALIZED (SELECT mention_id, min(mention_id) OVER (PARTITION BY e) AS entity_id FROM (SELECT s.mention_id, coalesce(g.entity_to, s.entity_id) AS e FROM {state} s LEFT JOIN {moves} g USING (mention_id)))"
