"""The same results in DuckDB SQL, written apart from the DataFrame plans."""

from __future__ import annotations

from erfocus.functions import features
from erfocus.functions.rand import sql_h32
from erfocus.plans import replays
from erfocus.sources import fixtures

Q = 3
SHARED = 3
#: Names of the watchlist; proposals of chains and of selections, and of blocks of the exhaustive view.
WATCH = 6
STEPS = 300
SELECT_STEPS = 600
RESOLVE_STEPS = 200
#: Grams that a large canopy shares with its query, and its chain's proposals.
LARGE_SHARED = 7
LARGE_STEPS = 200
#: Parallel rounds, and workers of each.
BSP_ROUNDS = 4
BSP_WORKERS = 24
ONE = "(SELECT min(query_id) FROM wl)"


def h(text: str) -> str:
    return sql_h32(text, "duckdb")


def grams(x: str) -> str:
    p = f"('##' || lower(trim({x}, ' ')) || '$$')"
    return f"list_distinct(list_transform(range(1, length({p}) - 1), lambda i: substr({p}, i, 3)))"


def toks(x: str) -> str:
    return f"list_filter(regexp_split_to_array(lower({x}), '[^a-z0-9]+'), lambda w: w <> '')"


def part(name: str = "m") -> str:
    return f"{name} AS ({fixtures.part_sql('duckdb')})"


def base(table: str = "", shared: int = SHARED, watch: int = WATCH) -> str:
    """Mentions, distinct strings with grams, the watchlist, its canopies."""
    return f"""{table or part()},
s AS (SELECT lower(trim(mention, ' ')) AS string, count(*) AS n_mentions FROM m GROUP BY 1),
sg AS (SELECT string, n_mentions, {grams('string')} AS gs FROM s),
wl AS MATERIALIZED (SELECT m.*, m.mention_id AS query_id, {grams('mention')} AS qg FROM m JOIN (SELECT gold, min(mention_id) AS mention_id FROM m WHERE lower(mention) = gold GROUP BY gold ORDER BY {h("'name|' || gold")}, gold LIMIT {watch}) USING (mention_id)),
{canopies(shared)}"""


def canopies(shared: int = SHARED) -> str:
    """Canopies of the queries in wl."""
    return f"""cs AS (SELECT query_id, string, len(list_intersect(gs, qg)) AS shared, len(list_intersect(gs, qg)) / (len(gs) + len(qg) - len(list_intersect(gs, qg))) AS sim
       FROM wl, sg WHERE len(list_intersect(gs, qg)) >= least({shared}, len(qg))),
canopy AS MATERIALIZED (SELECT query_id, mention_id, shared, sim FROM cs JOIN m ON lower(trim(m.mention, ' ')) = cs.string)"""


#: Whole canopies of the watchlist, and of its first query, each query's own mention among them.
ALL_OF = "c AS (SELECT query_id, mention_id FROM canopy UNION SELECT query_id, query_id FROM wl)"
OF_ONE = f"c1 AS (SELECT * FROM c WHERE query_id = {ONE})"


def sides(level: str, source: str = "m", kw: str = "[]::VARCHAR[]") -> str:
    ctx = "[]::VARCHAR[]" if level == "none" else f"list_distinct({level})"
    return f"sd AS MATERIALIZED (SELECT mention_id, lower(trim(mention, ' ')) AS m, {toks('mention')} AS toks, {ctx} AS ctx, {kw} AS kw, {grams('mention')} AS gs FROM {source})"


TEXT_SIM = "len(list_intersect(a.gs, b.gs)) / (len(a.gs) + len(b.gs) - len(list_intersect(a.gs, b.gs)))"


def feature(spec: features.FeatureSpec, similarity: str = TEXT_SIM) -> str:
    """A feature's weight for rows a and b of sides."""
    holds = {
        "f01": "a.m = b.m",
        "f02": "a.m[1] = b.m[1]",
        "f03": "a.m[2] = b.m[2] AND a.m[2] <> ''",
        "f04": "a.m[3] = b.m[3]",
        "f05": "contains(a.m, b.m) OR contains(b.m, a.m)",
        "f06": "length(a.m) = length(b.m)",
        "f07": "a.toks[1] = b.toks[1]",
        "f09": "list_has_any(a.toks, b.toks)",
        "f10": "list_has_any(a.toks, b.ctx) OR list_has_any(b.toks, a.ctx)",
        "f14": "list_has_any(a.ctx, b.ctx)",
    }
    n = spec.name
    if n == "f08":
        sim = f"round({similarity}, 9)"
        return f"CASE WHEN {sim} IS NULL THEN 0 " + " ".join(f"WHEN {sim} >= {least} THEN {w}" for least, w in spec.tiers) + f" ELSE {spec.lowest} END"
    if n == "f11":
        return f"CASE WHEN len(a.kw) = 0 AND len(b.kw) = 0 THEN 0 WHEN list_has_any(a.kw, b.ctx) OR list_has_any(b.kw, a.ctx) THEN {spec.plus} ELSE {spec.minus} END"
    if n == "f12":
        return f"CASE WHEN len(list_filter(b.kw, lambda k: contains(a.m, k))) + len(list_filter(a.kw, lambda k: contains(b.m, k))) > 0 THEN {spec.plus} ELSE {spec.minus} END"
    if n == "f13":
        return f"CASE WHEN len(list_filter(a.toks, lambda x: NOT list_contains(b.toks, x))) > 0 AND len(list_filter(b.toks, lambda x: NOT list_contains(a.toks, x))) > 0 THEN {spec.minus} ELSE {spec.plus} END"
    return f"CASE WHEN coalesce({holds[n]}, false) THEN {spec.plus} ELSE {spec.minus} END"


def weight(specs=features.PAIRWISE, similarity: str = TEXT_SIM) -> str:
    return " + ".join(f"({feature(s, similarity)})" for s in specs if s.klass != "entity" and (s.name == "f08" or s.plus or s.minus))


def vectors(source: str = "mem") -> str:
    """wv (component, mention_id, term, w): context vectors of unit length within each component; after sides()."""
    return f"""tm AS (SELECT component, mention_id, unnest(ctx) AS term FROM {source} JOIN sd USING (mention_id)),
nn AS (SELECT component, count(DISTINCT mention_id) AS n FROM tm GROUP BY 1),
idf AS (SELECT component, term, ln(max(n)::DOUBLE / count(*)) AS idf FROM tm JOIN nn USING (component) GROUP BY 1, 2),
wv AS MATERIALIZED (SELECT component, mention_id, term, idf / sqrt(sum(idf * idf) OVER (PARTITION BY component, mention_id)) AS w FROM tm JOIN idf USING (component, term) WHERE idf > 0)"""


def model(level: str, specs, cosines: bool, source: str = "m", kw: str = "[]::VARCHAR[]") -> str:
    """pw (component, i, j, w), i <= j, of members mem (component, mention_id): also each mention with itself."""
    pairs = "mem x JOIN mem y ON x.component = y.component AND x.mention_id <= y.mention_id JOIN sd a ON a.mention_id = x.mention_id JOIN sd b ON b.mention_id = y.mention_id"
    if not cosines:
        return f"{sides(level, source, kw)},\npw AS MATERIALIZED (SELECT x.component, x.mention_id AS i, y.mention_id AS j, ({weight(specs)})::BIGINT AS w FROM {pairs})"
    near = "CASE WHEN hx.mention_id IS NOT NULL AND hy.mention_id IS NOT NULL THEN coalesce(cv.cos, 0) END"
    return f"""{sides(level, source, kw)}, {vectors()},
cv AS MATERIALIZED (SELECT a.component, a.mention_id AS i, b.mention_id AS j, sum(a.w * b.w) AS cos FROM wv a JOIN wv b ON a.component = b.component AND a.term = b.term AND a.mention_id <= b.mention_id GROUP BY 1, 2, 3),
hv AS (SELECT DISTINCT component, mention_id FROM wv),
pw AS MATERIALIZED (SELECT x.component, x.mention_id AS i, y.mention_id AS j, ({weight(specs, near)})::BIGINT AS w FROM {pairs}
  LEFT JOIN cv ON cv.component = x.component AND cv.i = x.mention_id AND cv.j = y.mention_id LEFT JOIN hv hx ON hx.component = x.component AND hx.mention_id = x.mention_id LEFT JOIN hv hy ON hy.component = x.component AND hy.mention_id = y.mention_id)"""


def influenced(canopy: str = "c") -> str:
    """infl (query_id, mention_id, infl): the weights of canopies' mentions with the queries' own."""
    return f"infl AS (SELECT q.query_id, c.mention_id, w AS infl FROM qs q JOIN {canopy} c ON c.query_id = q.query_id JOIN pw ON pw.component = q.component AND pw.i = least(q.own, c.mention_id) AND pw.j = greatest(q.own, c.mention_id))"


WEIGHTED = {True: "wts0 AS (SELECT query_id, mention_id, weight FROM inv)", False: "wts0 AS (SELECT query_id, mention_id, weight FROM dec)"}


def setup(level: str, specs, cosines: bool, sampler: str = "influence_to_query", source: str = "m", kw: str = "[]::VARCHAR[]", canopy: str = "c") -> str:
    """From mem, qs and canopies to what chains draw from and are scored by."""
    inverse = sampler in ("expel", "expel_both")
    return f"""{model(level, specs, cosines, source, kw)},
{influenced(canopy)}, {INVERSE if inverse else DECAY}, {WEIGHTED[inverse]},
{replays.places()}"""


def influence(level: str = "document", specs=features.PAIRWISE, source: str = "canopy") -> str:
    return f"""{sides(level)},
infl AS (SELECT query_id, c.mention_id, ({weight(specs)})::BIGINT AS infl FROM {source} c JOIN sd a ON a.mention_id = c.mention_id JOIN sd b ON b.mention_id = c.query_id)"""


DECAY = """dec AS (SELECT *, least(0.05, 5.0 / n) * pow(1 - least(0.05, 5.0 / n), pos) AS weight
  FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY infl DESC, mention_id) - 1 AS pos, count(*) OVER (PARTITION BY query_id) AS n FROM infl))"""
INVERSE = """inv AS (SELECT *, CASE WHEN max(infl) OVER w = min(infl) OVER w THEN 1.0::DOUBLE ELSE 1.0::DOUBLE - (infl - min(infl) OVER w)::DOUBLE / (max(infl) OVER w - min(infl) OVER w) END AS weight
  FROM infl WINDOW w AS (PARTITION BY query_id))"""


def edges(level: str = "document", specs=features.PAIRWISE, source: str = "c", key: str = "query_id") -> str:
    """Edges of canopies; after sides()."""
    return f"e AS MATERIALIZED (SELECT x.{key}, x.mention_id AS i, y.mention_id AS j, ({weight(specs)})::BIGINT AS w FROM {source} x JOIN {source} y ON x.{key} = y.{key} AND x.mention_id < y.mention_id JOIN sd a ON a.mention_id = x.mention_id JOIN sd b ON b.mention_id = y.mention_id)"


#: cls (mention_id, rep) of c1, after sides(): mentions of equal strings, whose contexts are alike in the canopy's tokens and in common words.
CLASSES = """cw AS (SELECT mention_id, unnest(ctx) AS word FROM sd JOIN c1 USING (mention_id)),
common AS (SELECT word, count(*) = (SELECT count(*) FROM c1) AS of_all FROM cw GROUP BY 1 HAVING count(*) > 1),
told AS (SELECT unnest(toks) AS word FROM sd JOIN c1 USING (mention_id) UNION SELECT word FROM common WHERE NOT (SELECT coalesce(bool_or(of_all), false) FROM common) UNION SELECT min(word) FROM common WHERE of_all),
cx AS (SELECT mention_id, list_sort(list(word)) AS words FROM cw WHERE word IN (SELECT word FROM told) GROUP BY 1),
cls AS (SELECT mention_id, min(mention_id) OVER (PARTITION BY m, toks, words) AS rep FROM c1 JOIN sd USING (mention_id) LEFT JOIN cx USING (mention_id)),
many AS (SELECT rep, count(*) AS n FROM cls GROUP BY 1)"""


def states(source: str) -> str:
    """Three initial states of one canopy."""
    return f"""st AS (
SELECT 'singletons' AS how, mention_id, mention_id AS entity_id FROM {source}
UNION ALL SELECT 'single', mention_id, min(mention_id) OVER () FROM {source}
UNION ALL SELECT 'random', mention_id, min(mention_id) OVER (PARTITION BY {h("'init|1|' || mention_id")} % 8) FROM {source})"""


def one_canopy(level: str = "paragraph", specs=features.TWO_WORD_NAMES, cosines: bool = False, sampler: str = "influence_to_query") -> str:
    """The first query's whole canopy as a component."""
    return f"""{base()}, {ALL_OF}, mem AS (SELECT query_id AS component, mention_id FROM c WHERE query_id = {ONE}), qs AS (SELECT {ONE} AS component, {ONE} AS query_id, {ONE} AS own),
{setup(level, specs, cosines, sampler)}"""


NAMED = "CASE WHEN {0} = 0 THEN -1 ELSE ids[{0}] END"
TRACE = f"SELECT t::INTEGER AS step, ids[mv] AS m, {NAMED.format('src')} AS e_from, {NAMED.format('dst')} AS e_to, delta::BIGINT AS delta, ok AS accepted FROM ch JOIN con USING (component) WHERE t >= 0"


def chain_key(sampler: str, **options) -> str:
    return f"""WITH RECURSIVE {one_canopy(sampler=sampler)}, {replays.chain(sampler, STEPS, **options)}
{TRACE}"""


def selected(steps: int, queries: str, components: str, **options) -> str:
    """Members of queries' entities after chains over components of whole canopies."""
    return f"""WITH RECURSIVE {base()}, {ALL_OF}, {components}, {queries}, {setup('paragraph', features.TWO_WORD_NAMES, True)}, {replays.chain('influence_to_query', steps, **options)}
SELECT query_id, mention_id FROM ({replays.members_of_queries(steps - 1)})"""


EACH = "mem AS (SELECT query_id AS component, mention_id FROM c)", "qs AS (SELECT query_id AS component, query_id, query_id AS own FROM wl)"
FIRST = f"mem AS (SELECT query_id AS component, mention_id FROM c WHERE query_id = {ONE})", f"qs AS (SELECT {ONE} AS component, {ONE} AS query_id, {ONE} AS own)"


def merged() -> tuple[str, str]:
    links = closure("SELECT DISTINCT x.query_id AS i, y.query_id AS j FROM c x JOIN c y USING (mention_id) WHERE x.query_id < y.query_id", "SELECT query_id AS x FROM wl")
    return f"{links}, mem AS (SELECT DISTINCT component, mention_id FROM c JOIN cc ON cc.node = c.query_id)", "qs AS (SELECT component, node AS query_id, node AS own FROM cc)"


#: The declared template, beside the table.
TEMPLATE = """mt AS (SELECT mention_id, mention, paragraph, document, []::VARCHAR[] AS kw FROM m UNION ALL SELECT -1, 'red plate', [], [], ['topic_red_plate'])"""


def by_template(tail: str, level: str = "paragraph", specs=features.TWO_WORD_NAMES, cosines: bool = True) -> str:
    watch = f"wl AS (SELECT -1 AS query_id, {grams("'red plate'")} AS qg)"
    blocked = base().split("wl AS MATERIALIZED")[0] + watch + ",\n" + canopies()
    return f"""WITH RECURSIVE {blocked}, {ALL_OF}, {TEMPLATE}, mem AS (SELECT -1 AS component, mention_id FROM c), qs AS (SELECT -1 AS component, -1 AS query_id, -1 AS own),
{setup(level, specs, cosines, source='mt', kw='kw')}, {replays.chain('influence_to_query', SELECT_STEPS)},
found AS ({replays.members_of_queries(SELECT_STEPS - 1)})
{tail}"""


def parallel_setup() -> str:
    """Alias tables, weights and the initial state of the watchlist's merged canopies."""
    return f"""{base()}, {ALL_OF}, {influence('paragraph', features.TWO_WORD_NAMES, 'c')}, {DECAY},
mem AS (SELECT DISTINCT 0 AS component, mention_id FROM c),
pw AS MATERIALIZED (SELECT x.mention_id AS i, y.mention_id AS j, ({weight(features.TWO_WORD_NAMES)})::BIGINT AS w FROM mem x JOIN mem y ON x.mention_id < y.mention_id JOIN sd a ON a.mention_id = x.mention_id JOIN sd b ON b.mention_id = y.mention_id),
both_ways AS MATERIALIZED (SELECT i, j, w FROM pw UNION ALL SELECT j, i, w FROM pw),
{ALIASES}, st0 AS (SELECT mention_id, mention_id AS entity_id FROM mem)"""


#: tabs (query_id, ids, pr, al): alias tables of dec's weights.
ALIASES = f"""aw AS (SELECT query_id AS component, query_id, mention_id AS p, weight AS w FROM dec), {replays.aliased('aw')},
tabs AS MATERIALIZED (SELECT query_id, ids, pr, al FROM tables JOIN (SELECT query_id, list(mention_id ORDER BY mention_id) AS ids FROM dec GROUP BY 1) USING (query_id))"""


def designed(table: str, picked: str, sizes: list[tuple[int, int]]) -> str:
    """Workloads' canopies: d (query_id, mention_id), wanted (query_id, gold, own, sel, size); picked: what has labels' topic words."""
    rows = ", ".join(f"({i + 1}, {s}, {n})" for i, (s, n) in enumerate(sizes))
    return f"""{table}, {picked},
s AS (SELECT lower(trim(mention, ' ')) AS string, {grams('mention')} AS gs FROM m GROUP BY ALL),
wanted AS MATERIALIZED (SELECT query_id, gold, own, sel, size FROM (SELECT gold, own, row_number() OVER (ORDER BY {h("'name|' || gold")}, gold) AS query_id FROM (SELECT gold, min(mention_id) AS own FROM mp WHERE lower(mention) = gold AND list_contains(paragraph, 'topic_' || replace(gold, ' ', '_')) GROUP BY 1))
  JOIN (VALUES {rows}) AS v(query_id, sel, size) USING (query_id)),
same AS (SELECT query_id, mention_id FROM (SELECT query_id, mention_id, sel, row_number() OVER (PARTITION BY query_id ORDER BY mention_id) AS k FROM m JOIN wanted USING (gold) WHERE mention_id <> own) WHERE k < sel),
wq AS (SELECT wanted.*, {grams('mention')} AS qg FROM wanted JOIN m ON m.mention_id = own),
hits AS (SELECT query_id, string, wq.gold, size, sel, len(list_intersect(gs, qg)) AS shared FROM wq, s WHERE len(list_intersect(gs, qg)) >= least(2, len(qg))),
oth AS (SELECT query_id, m.mention_id, shared, size, sel, row_number() OVER (PARTITION BY query_id, m.gold ORDER BY shared DESC, m.mention_id) AS turn FROM hits JOIN m ON lower(trim(m.mention, ' ')) = string WHERE m.gold <> hits.gold),
pick AS (SELECT query_id, mention_id FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY turn, shared DESC, mention_id) AS k FROM oth) WHERE k <= size - sel),
d AS MATERIALIZED (SELECT * FROM same UNION SELECT * FROM pick UNION SELECT query_id, own FROM wanted), mem AS (SELECT query_id AS component, mention_id FROM d), qs AS (SELECT query_id AS component, query_id, own FROM wanted),
gold AS (SELECT mention_id, gold FROM m)"""


SAME = "mp AS (SELECT * FROM m)"
WITHOUT_TOPICS = "mp AS (SELECT * REPLACE (['topic_' || replace(gold, ' ', '_')] AS paragraph) FROM m)"


def compared(kind: str, informative: int, picked: str, temperature: float | None = None) -> str:
    """One sampler's rows of a comparison."""
    size, samples, runs = 300, 2500, 10
    table = f"m AS MATERIALIZED ({fixtures.part_sql('duckdb', informative=informative)})"
    return f"""SELECT * FROM (WITH RECURSIVE {designed(table, picked, [(k, size) for k in (11, 46, 130)])}, {setup('paragraph', features.TWO_WORD_NAMES, True, kind, canopy='d')},
{replays.chain(kind, samples, runs=runs, temperature=temperature)}, {replays.accuracy()},
fin AS (SELECT component, run, min(t + 1) FILTER (f1q >= 0.95 AND t >= 0) AS first_step, arg_max(f1q, t) AS f1q, min(t + 1) FILTER (f1q >= 0.95) AS any_step FROM f GROUP BY 1, 2),
tr AS (SELECT component, count(*) AS selectivity FROM mem JOIN gold USING (mention_id) JOIN wanted w ON w.query_id = component AND w.gold = gold.gold GROUP BY 1)
SELECT '{kind}' AS sampler, component AS query_id, selectivity, round(avg(f1q), 9) AS f1_at_budget, round(stddev(f1q), 9) AS sd, round(avg(any_step), 9) AS steps_to_target, count(any_step) AS runs_reached, count(*) AS runs FROM fin JOIN tr USING (component) GROUP BY 1, 2, 3)"""


def closure(edges_sql: str, nodes_sql: str) -> str:
    """Smallest node reachable over a relation of few pairs; both ways are added."""
    return f"""lk AS ({edges_sql}), nd AS ({nodes_sql}),
rc(a, b) AS (SELECT x, x FROM nd UNION SELECT rc.a, l2.j FROM rc JOIN (SELECT i, j FROM lk UNION ALL SELECT j, i FROM lk) l2 ON l2.i = rc.b),
cc AS (SELECT a AS node, min(b) AS component FROM rc GROUP BY 1)"""


STRINGS = "ss AS (SELECT mention_id, gold, min(mention_id) OVER (PARTITION BY lower(trim(mention, ' '))) AS entity_id FROM m)"

PRF = f"""{STRINGS},
pr AS (SELECT w.query_id, count(*) FILTER (s.mention_id <> w.query_id AND s.entity_id = o.entity_id AND s.gold = w.gold) AS tp,
  count(*) FILTER (s.mention_id <> w.query_id AND s.entity_id = o.entity_id) AS n_answer, count(*) FILTER (s.mention_id <> w.query_id AND s.gold = w.gold) AS n_gold
  FROM wl w JOIN ss o ON o.mention_id = w.query_id, ss s GROUP BY 1),
prf AS (SELECT *, CASE WHEN n_answer > 0 THEN tp / n_answer ELSE 0.0 END AS precision, CASE WHEN n_gold > 0 THEN tp / n_gold ELSE 0.0 END AS recall,
  CASE WHEN tp > 0 THEN 2.0 * tp / (n_answer + n_gold) ELSE 0.0 END AS f1q FROM pr)"""

SCRIPT = f"sc AS (SELECT (user_id % 9)::BIGINT AS query_id, event_id AS step, {h("'acc|' || event_id")} % 10 < user_id % 9 AS accepted FROM events)"
RATES = f"{SCRIPT}, rt AS (SELECT query_id, avg(accepted::INT) AS rate FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY step DESC) AS k FROM sc) WHERE k <= 50 GROUP BY 1)"


def shares(total: int, weight_sql: str) -> str:
    return f"""x0 AS (SELECT query_id, sel, {total} * {weight_sql} / sum({weight_sql}) OVER () AS x FROM sl),
x1 AS (SELECT *, floor(x)::BIGINT AS b, {total} - sum(floor(x)::BIGINT) OVER () AS lft, row_number() OVER (ORDER BY round(x - floor(x), 9) DESC, query_id) AS r FROM x0),
x2 AS (SELECT query_id, sel, b + CASE WHEN r <= lft THEN 1 ELSE 0 END AS k FROM x1)"""


SEL = f"{base()}, sl AS (SELECT query_id, count(*) AS sel FROM canopy GROUP BY 1)"

#: The few mentions of exact inference, all their partitions as lists by place, scores and probabilities.
FEW = f"""{part('pm')},
nm AS (SELECT *, row_number() OVER (ORDER BY {h("'name|' || gold")}, gold) AS r FROM (SELECT gold, min(mention_id) AS first FROM pm WHERE lower(mention) = gold GROUP BY gold)),
rk AS (SELECT pm.*, r, row_number() OVER (PARTITION BY r ORDER BY mention_id <> first, mention_id) AS k FROM pm JOIN nm USING (gold) WHERE r <= {len(fixtures.FEW)}),
m AS MATERIALIZED (SELECT mention_id, doc_id, mention, paragraph, gold FROM rk WHERE k <= {list(fixtures.FEW)}[r]), own AS (SELECT first AS own FROM nm WHERE r = 1),
idl AS (SELECT list(mention_id ORDER BY mention_id) AS ids, count(*) AS size FROM m), {sides('paragraph')},
c AS (SELECT 0 AS query_id, mention_id FROM m), {edges('paragraph', features.CONTEXT_FIRST)},
gr(k, p) AS (SELECT 1, [1] UNION ALL SELECT k + 1, list_append(p, x) FROM (SELECT k, p, unnest(list_append(list_distinct(p), k + 1)) AS x FROM gr WHERE k < (SELECT size FROM idl))),
ep AS (SELECT list_position(ids, i) AS a, list_position(ids, j) AS b, w FROM e, idl),
pt AS (SELECT p, coalesce((SELECT sum(w) FROM ep WHERE p[a] = p[b]), 0)::BIGINT AS score FROM gr WHERE k = (SELECT size FROM idl)),
z AS (SELECT p, score, exp((score - max(score) OVER ()) / 100.0) AS z FROM pt),
po AS (SELECT p, score, z / sum(z) OVER () AS prob FROM z),
spot AS (SELECT list_position(ids, own) AS spot FROM idl, own), ks AS (SELECT unnest(range(1, size + 1)) AS k FROM idl)"""

VEC = f"""vm AS (SELECT DISTINCT mention_id FROM canopy WHERE query_id = {ONE} UNION SELECT {ONE}),
tm AS (SELECT mention_id, unnest(list_distinct(document)) AS term FROM m WHERE mention_id IN (SELECT mention_id FROM vm)),
idf AS (SELECT term, ln((SELECT count(DISTINCT mention_id) FROM tm)::DOUBLE / count(*)) AS idf FROM tm GROUP BY 1),
wv AS (SELECT mention_id, term, idf / sqrt(sum(idf * idf) OVER (PARTITION BY mention_id)) AS w FROM tm JOIN idf USING (term) WHERE idf > 0)"""


GOLD = "gold AS (SELECT mention_id, gold FROM m)"

#: What direction each canopy of the watchlist calls for; the weights are those of chains, with cosines.
DIRECTED = f"""way AS MATERIALIZED (SELECT * FROM (WITH {EACH[0]}, {EACH[1]}, {model('paragraph', features.TWO_WORD_NAMES, True)}, {influenced()} SELECT query_id, CASE WHEN avg((infl > 0)::INT) > 0.5 THEN 'expel' ELSE 'influence_to_query' END AS direction FROM infl GROUP BY 1))"""


def vector_planes(n: int, dims: int = 64, seed: int = 1) -> str:
    """blocks (mention_id, block): signs of vectors' products with planes made of hashes."""
    planes = f"pl AS (SELECT p, list({h(f"'{seed}|' || p || '|' || d")} / 2147483648.0 - 1.0 ORDER BY d) AS ws FROM range(0, {n}) AS a(p), range(0, {dims}) AS b(d) GROUP BY 1)"
    return f"{planes}, blocks AS (SELECT vec_id AS mention_id, string_agg(CASE WHEN list_sum(list_transform(embedding, lambda x, i: x::DOUBLE * ws[i])) > 0 THEN '1' ELSE '0' END, '' ORDER BY p) AS block FROM embeddings, pl GROUP BY 1)"


#: Mentions of event handles that share grams with a watchlist of five.
HANDLES = f"""ev AS (SELECT event_id AS mention_id, ts, user_id::VARCHAR AS gold, CASE WHEN {h("'v|' || event_id")} % 4 = 0 THEN substr('user' || user_id, 1, length('user' || user_id) - 1) ELSE 'user' || user_id END AS mention FROM events),
hw AS (SELECT DISTINCT gold::BIGINT AS query_id, mention FROM ev WHERE mention = 'user' || gold ORDER BY 1 LIMIT 5), hq AS (SELECT query_id, {grams('mention')} AS own FROM hw),
hs AS (SELECT mention, {grams('mention')} AS gs FROM (SELECT DISTINCT mention FROM ev)), hm AS (SELECT query_id, mention_id, ts FROM hq, hs JOIN ev USING (mention) WHERE len(list_intersect(own, gs)) >= least(6, len(own)))"""


def in_context(label: str, of_query: str, words: bool, level: str) -> str:
    """One row of the context workload: the query's own context and keywords changed."""
    keep = {"none": (), "paragraph": ("paragraph",), "document": ("paragraph", "document")}[of_query]
    column = lambda c: c if c in keep else "[]::VARCHAR[]"
    kw = "['topic_' || replace(m.gold, ' ', '_')]" if words else "[]::VARCHAR[]"
    changed = f"mc AS (SELECT mention_id, mention, CASE WHEN mention_id = own THEN {column('paragraph')} ELSE paragraph END AS paragraph, CASE WHEN mention_id = own THEN {column('document')} ELSE document END AS document, CASE WHEN mention_id = own THEN {kw} ELSE []::VARCHAR[] END AS kw FROM m, (SELECT own FROM wanted))"
    return f"""SELECT * FROM (WITH RECURSIVE {designed(f"m AS MATERIALIZED ({fixtures.part_sql('duckdb')})", SAME, [(46, 103)])}, {changed}, {setup(level, features.TWO_WORD_NAMES, True, 'expel', 'mc', 'kw', 'd')},
{replays.chain('expel', 600, runs=6)}, {replays.accuracy()} SELECT '{label}' AS level, round(avg(f1q) FILTER (t = -1), 9) AS f1_start, round(avg(f1q) FILTER (t = 599), 9) AS f1_end, round(stddev(f1q) FILTER (t = 599), 9) AS sd FROM f)"""


def worked(kind: str) -> str:
    """One sampler's row of the worked example."""
    return f"""SELECT * FROM (WITH RECURSIVE {FEW}, mem AS (SELECT 0 AS component, mention_id FROM m), qs AS (SELECT 0 AS component, 0 AS query_id, own FROM own),
pw AS (SELECT 0 AS component, x.mention_id AS i, y.mention_id AS j, ({weight(features.CONTEXT_FIRST)})::BIGINT AS w FROM mem x JOIN mem y ON x.mention_id <= y.mention_id JOIN sd a ON a.mention_id = x.mention_id JOIN sd b ON b.mention_id = y.mention_id),
{influenced()}, {INVERSE if kind in ('expel', 'expel_both') else DECAY}, {WEIGHTED[kind in ('expel', 'expel_both')]}, {replays.places()}, {replays.chain(kind, 400, runs=20)},
sc AS (SELECT run, coalesce((SELECT sum(w) FROM ep WHERE nxt[a] = nxt[b]), 0) AS score FROM ch WHERE t = 399)
SELECT '{kind}' AS sampler, max(score)::BIGINT AS best_score, avg(score) AS mean_score, (SELECT max(score) FROM po)::BIGINT AS exact_score FROM sc)"""


def oracle_sql() -> dict[str, str]:
    two = features.TWO_WORD_NAMES
    out = {
        "line_mentions": f"SELECT mention_id, doc_id, startpos, mention, array_to_string(document, ' ') AS words, gold FROM ({fixtures.line_sql('duckdb', 'part')})",
        "customer_mentions": f"SELECT mention_id, mention, array_to_string(document, ' ') AS words, gold FROM ({fixtures.customer_sql('duckdb')})",
        "qgram_postings": f"WITH {base()} SELECT unnest(gs) AS gram, string FROM sg",
        "gram_df": f"WITH {base()} SELECT gram, count(*) AS n_strings, sum(n_mentions)::BIGINT AS n_mentions FROM (SELECT unnest(gs) AS gram, n_mentions FROM sg) GROUP BY 1",
        "canopy_single": f"WITH {base()} SELECT query_id, mention_id, shared::BIGINT AS shared, round(sim, 6) AS sim FROM canopy WHERE query_id = {ONE}",
        "canopy_watchlist": f"WITH {base()} SELECT query_id, mention_id, shared::BIGINT AS shared, round(sim, 6) AS sim FROM canopy",
        "canopy_rarest_grams": f"WITH {base()} SELECT query_id, mention_id, shared::BIGINT AS shared, round(sim, 6) AS sim FROM canopy",
        "canopy_sorted_neighborhood": f"""WITH {part()}, r AS (SELECT mention_id, row_number() OVER (ORDER BY lower(trim(mention, ' ')), mention_id) AS k FROM m)
SELECT least(x.mention_id, y.mention_id) AS a, greatest(x.mention_id, y.mention_id) AS b FROM r x JOIN r y ON y.k IN (x.k + 1, x.k + 2)""",
        "watchlist_selectivity": f"WITH {base()} SELECT query_id, count(*) AS sel FROM canopy GROUP BY 1",
        "gold_selectivity": f"WITH {base()} SELECT query_id, (SELECT count(*) FROM m WHERE gold = wl.gold) AS sel FROM wl",
        "canopy_quality": f"WITH {base()} SELECT query_id, count(*) AS n, round(avg((m.gold = wl.gold)::INT), 9) AS quality FROM canopy JOIN wl USING (query_id) JOIN m ON m.mention_id = canopy.mention_id GROUP BY 1",
        "merged_components": f"""WITH RECURSIVE {base()}, {closure("SELECT DISTINCT x.query_id AS i, y.query_id AS j FROM canopy x JOIN canopy y USING (mention_id) WHERE x.query_id < y.query_id", "SELECT query_id AS x FROM wl")}
SELECT node AS query_id, component FROM cc""",
        "term_stats": r"""WITH t AS (SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(text), '[\s.,]+'), lambda w: w <> '')) AS term FROM documents)
SELECT term, count(DISTINCT doc_id) AS df, count(*) AS tf FROM t GROUP BY 1""",
        "tfidf_cosine": f"""WITH {base()}, {VEC}
SELECT {ONE} AS query_id, vm.mention_id, round(coalesce((SELECT sum(a.w * b.w) FROM wv a JOIN wv b USING (term) WHERE a.mention_id = {ONE} AND b.mention_id = vm.mention_id), 0.0), 6) AS cos FROM vm""",
        "pair_features": f"""WITH {base()}, {sides('document')} SELECT query_id, c.mention_id, {", ".join(f"({feature(s)})::BIGINT AS {s.name}" for s in features.PAIRWISE)}
FROM canopy c JOIN sd a ON a.mention_id = c.mention_id JOIN sd b ON b.mention_id = c.query_id""",
        "pair_edges": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {sides('document')}, {CLASSES},
  e AS (SELECT a.mention_id AS i, b.mention_id AS j, ({weight()})::BIGINT AS w FROM sd a JOIN sd b ON a.mention_id <= b.mention_id JOIN many x ON x.rep = a.mention_id JOIN many y ON y.rep = b.mention_id WHERE a.mention_id < b.mention_id OR x.n > 1)
  SELECT 'member' AS what, mention_id AS a, rep AS b, NULL::BIGINT AS w FROM cls UNION ALL SELECT 'pair', i, j, w FROM e""",
        "influence_scores": f"WITH {base()}, {influence()} SELECT query_id, mention_id, infl FROM infl",
        "influence_decay": f"WITH {base()}, {influence()}, {DECAY} SELECT query_id, mention_id, pos::INTEGER AS pos, round(weight, 9) AS weight FROM dec",
        "influence_decay_by_score": f"""WITH {base()}, {influence()}, d AS (SELECT *, CASE WHEN hi = lo THEN 0 ELSE floor(100 * (hi - infl)::DOUBLE / (hi - lo)) END::INTEGER AS pos
FROM (SELECT *, max(infl) OVER (PARTITION BY query_id) AS hi, min(infl) OVER (PARTITION BY query_id) AS lo FROM infl)) SELECT query_id, mention_id, pos, round(0.05 * pow(0.95, pos), 9) AS weight FROM d""",
        "inverse_influence": f"WITH {base()}, {influence()}, {INVERSE} SELECT query_id, mention_id, round(weight, 9) AS weight FROM inv",
        "influence_top": f"WITH {base()}, {influence()} SELECT query_id, mention_id, infl FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY infl DESC, mention_id) AS k FROM infl) WHERE k <= 20 AND infl >= -400",
        "alias_mass": f"WITH {base()}, {influence()}, {DECAY} SELECT query_id, mention_id, round(weight / sum(weight) OVER (PARTITION BY query_id), 9) AS p FROM dec",
        "alias_bytes": f"WITH {base()} SELECT query_id, (12 * count(*))::BIGINT AS bytes FROM canopy GROUP BY 1",
        "init_states": f"WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')} SELECT how, mention_id, entity_id FROM st",
        "config_score": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')}, {sides('document')}, {edges(source='c1')}
SELECT a.how, sum(CASE WHEN a.entity_id = b.entity_id THEN w ELSE 0 END)::BIGINT AS score FROM e JOIN st a ON a.mention_id = e.i JOIN st b ON b.mention_id = e.j AND a.how = b.how GROUP BY 1""",
        "entity_score": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')}, {sides('document')}, {edges(source='c1')},
r AS (SELECT how, st.mention_id, entity_id, doc_id, count(*) OVER (PARTITION BY how, entity_id) AS n, count(*) OVER (PARTITION BY how, entity_id, doc_id) AS k FROM st JOIN m USING (mention_id)),
b AS (SELECT i AS x, j AS y FROM e WHERE w > 0 UNION ALL SELECT j, i FROM e WHERE w > 0),
nr AS (SELECT DISTINCT a.how, a.mention_id FROM st a JOIN b ON b.x = a.mention_id JOIN st o ON o.how = a.how AND o.mention_id = b.y AND o.entity_id = a.entity_id),
s2 AS (SELECT r.*, nr.mention_id IS NOT NULL AS near FROM r LEFT JOIN nr ON nr.how = r.how AND nr.mention_id = r.mention_id)
SELECT how, sum(CASE WHEN n < 2 THEN 0 ELSE CASE WHEN k > 1 THEN 350 ELSE -15 END + CASE WHEN near THEN 100 ELSE -5 END END)::BIGINT AS score FROM s2 GROUP BY 1""",
        "matching_strings": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')}, r AS (SELECT entity_id, lower(trim(mention, ' ')) AS s FROM st JOIN m USING (mention_id) WHERE how = 'random')
SELECT a.entity_id AS entity_a, b.entity_id AS entity_b, count(*) AS n FROM r a JOIN r b ON a.s = b.s AND a.entity_id < b.entity_id GROUP BY 1, 2""",
        "move_delta": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')}, {sides('document')}, {edges(source='c1')},
r AS (SELECT mention_id, entity_id FROM st WHERE how = 'random'), b AS (SELECT i AS x, j AS y, w FROM e UNION ALL SELECT j, i, w FROM e), t AS (SELECT DISTINCT entity_id AS entity_to FROM r)
SELECT r.mention_id, r.entity_id AS entity_from, entity_to, CASE WHEN r.entity_id = entity_to THEN 0 ELSE
  (SELECT coalesce(sum(CASE WHEN o.entity_id = t.entity_to THEN w WHEN o.entity_id = r.entity_id THEN -w ELSE 0 END), 0) FROM b JOIN r o ON o.mention_id = b.y WHERE b.x = r.mention_id) END::BIGINT AS delta FROM r, t""",
        "schedule_round_robin": f"WITH {SEL}, q AS (SELECT query_id, row_number() OVER (ORDER BY query_id) - 1 AS i, count(*) OVER () AS n FROM sl) SELECT s::INTEGER AS slot, query_id, least(100, 1950 - s * 100)::INTEGER AS k FROM range(0, 20) AS r(s) JOIN q ON s % n = i",
        "schedule_equal": f"WITH {SEL}, {shares(1950, '1')} SELECT (row_number() OVER (ORDER BY query_id) - 1)::INTEGER AS slot, query_id, k::INTEGER AS k FROM x2 WHERE k > 0",
        "schedule_by_selectivity": f"""WITH {SEL}, {shares(1950, 'sel')}, y AS (SELECT query_id, sel, k, unnest(range(0, k, 100)) AS a FROM x2)
SELECT (row_number() OVER (ORDER BY (a // 100) / ceil(k / 100), sel DESC, query_id) - 1)::INTEGER AS slot, query_id, least(100, k - a)::INTEGER AS k FROM y""",
        "acceptance_rates": f"WITH {SCRIPT} SELECT query_id, step, round(avg(accepted::INT) OVER (PARTITION BY query_id ORDER BY step ROWS 49 PRECEDING), 9) AS rate FROM sc",
        "schedule_closest_first": f"WITH {RATES} SELECT query_id, round(rate, 9) AS rate FROM rt WHERE rate > 0 ORDER BY rt.rate, query_id LIMIT 1",
        "schedule_farthest_first": f"WITH {RATES} SELECT query_id, round(rate, 9) AS rate FROM rt ORDER BY rt.rate DESC, query_id LIMIT 1",
        "schedule_slowest_first": f"WITH {RATES} SELECT query_id, round(rate, 9) AS rate FROM rt ORDER BY rt.rate, query_id LIMIT 1",
        "query_prf": f"WITH {base()}, {PRF} SELECT query_id, tp, n_answer, n_gold, round(precision, 9) AS precision, round(recall, 9) AS recall, round(f1q, 9) AS f1q FROM prf",
        "mean_f1q": f"WITH {base()}, {PRF} SELECT count(*) AS n_queries, round(avg(f1q), 9) AS mean_f1q FROM prf",
        "metric_cube": f"WITH {base()}, {PRF} SELECT n_gold, query_id, count(*) AS n, round(avg(f1q), 9) AS f1q FROM prf GROUP BY CUBE (n_gold, query_id)",
        "average_runs": f"WITH {base()}, {PRF} SELECT n_gold, round(avg(f1q), 9) AS mean, round(coalesce(stddev(f1q), 0.0), 9) AS sd, count(*) AS n_runs FROM prf GROUP BY 1",
        "b_cubed": f"""WITH {part()}, {STRINGS}, k AS (SELECT *, count(*) OVER (PARTITION BY entity_id, gold) AS b, count(*) OVER (PARTITION BY entity_id) AS e, count(*) OVER (PARTITION BY gold) AS g FROM ss),
p AS (SELECT avg(b / e) AS p, avg(b / g) AS r FROM k) SELECT round(p, 9) AS precision, round(r, 9) AS recall, round(2 * p * r / (p + r), 9) AS f1 FROM p""",
        "query_ratios": f"WITH {base()}, x AS (SELECT (SELECT count(*) FROM wl) AS n_queries, count(DISTINCT gold) AS n_entities, count(*) AS n_mentions FROM m) SELECT n_queries, n_entities, n_mentions, round(n_queries / n_entities, 9) AS queries_per_entity, round(n_mentions / n_entities, 9) AS mentions_per_entity FROM x",
        "pairwise_closure": f"""WITH RECURSIVE {base()}, {ALL_OF}, {OF_ONE}, {sides('document')}, {edges(source='c1')}, {closure("SELECT i, j FROM e WHERE w >= 60", "SELECT mention_id AS x FROM c1")}
SELECT node AS mention_id, component AS entity_id FROM cc""",
        "blocked_baseline": "SELECT p_partkey AS mention_id, min(p_partkey) OVER (PARTITION BY p_brand) AS entity_id FROM part",
        "coref_view": f"WITH {part()}, {STRINGS} SELECT a.mention_id AS a, b.mention_id AS b FROM ss a JOIN ss b ON a.entity_id = b.entity_id AND a.mention_id < b.mention_id",
        "clusters": f"WITH {part()}, {STRINGS} SELECT entity_id, string_agg(mention_id, ',' ORDER BY mention_id) AS mentions, count(*) AS n FROM ss GROUP BY 1",
        "same_entity": f"WITH {part()}, {STRINGS} SELECT x.mention_id AS a, y.mention_id AS b, x.entity_id = y.entity_id AS same_entity FROM ss x JOIN ss y ON y.mention_id = x.mention_id + 64",
        "context_levels": " UNION ALL ".join(f"SELECT '{v}' AS level, * FROM (WITH {base()}, {influence(v)} SELECT query_id, mention_id, infl FROM infl)" for v in features.LEVELS),
        "exact_posterior": f"WITH RECURSIVE {FEW} SELECT array_to_string(p, '') AS partition, score, round(prob, 9) AS prob FROM po",
        "exact_map": f"WITH RECURSIVE {FEW}, b AS (SELECT p FROM po ORDER BY score DESC, p LIMIT 1) SELECT ids[k] AS mention_id FROM b, idl, spot, ks WHERE p[k] = p[spot]",
        "exact_marginal": f"WITH RECURSIVE {FEW} SELECT ids[k] AS mention_id, round(sum(CASE WHEN p[k] = p[spot] THEN prob ELSE 0 END), 9) AS p_coref FROM po, idl, spot, ks GROUP BY 1",
        "bsp_winners": f"""WITH p AS (SELECT p_partkey % 7 AS query_id, p_partkey AS n, p_partkey AS mention_id, p_partkey % 50 AS entity_from, 1000 + {h("'to|' || p_partkey")} % 20 AS entity_to FROM part),
k AS (SELECT *, {h("'1|0|p|' || query_id || '|' || n")} AS pr FROM p), c AS (SELECT entity_from AS en, pr, query_id, n FROM k UNION ALL SELECT entity_to, pr, query_id, n FROM k),
f AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY en ORDER BY pr, query_id, n) AS r FROM c) WHERE r = 1)
SELECT k.query_id, k.n, k.mention_id, k.entity_from, k.entity_to FROM k JOIN f a ON a.en = k.entity_from AND a.query_id = k.query_id AND a.n = k.n JOIN f b ON b.en = k.entity_to AND b.query_id = k.query_id AND b.n = k.n""",
        "passage_watchlist": "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)",
        "email_mentions": f"""WITH h AS (SELECT doc_id, text, regexp_extract_all(text, '{fixtures.EMAIL}') AS hits, regexp_split_to_array(text, '{fixtures.EMAIL}') AS gaps FROM documents WHERE regexp_matches(text, '{fixtures.EMAIL}')),
r AS (SELECT *, unnest(range(1, len(hits) + 1)) AS k FROM h)
SELECT doc_id, (1 + list_sum(list_transform(gaps[1:k], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:k - 1], lambda x: length(x))), 0))::INTEGER AS startpos, hits[k] AS mention FROM r""",
        "trace_curve": f"WITH RECURSIVE {one_canopy()}, {replays.chain('influence_to_query', STEPS)}, {GOLD}, {replays.accuracy()} SELECT t::INTEGER AS step, round(f1q, 9) AS f1q FROM f WHERE t BETWEEN 0 AND 49",
        "time_to_target": f"WITH RECURSIVE {one_canopy()}, {replays.chain('influence_to_query', STEPS)}, {GOLD}, {replays.accuracy()} SELECT {ONE} AS query_id, min((t + 1)::INTEGER) FILTER (f1q >= 0.5) AS first_step FROM f",
        "score_trace": f"WITH RECURSIVE {one_canopy()}, {replays.chain('influence_to_query', STEPS)} SELECT t::INTEGER AS step, (sum(delta * ok::INT) OVER (ORDER BY t))::BIGINT AS score FROM ch WHERE t >= 0",
        "proposal_counts": f"WITH RECURSIVE {one_canopy()}, {replays.chain('uniform', STEPS)} SELECT count(*) AS proposals, count(*) FILTER (ok) AS accepted, round(avg(ok::INT), 9) AS rate, min(t::INTEGER) FILTER (ok) AS first_accepted FROM ch WHERE t >= 0",
        "first_correct": f"WITH RECURSIVE {one_canopy()}, {replays.chain('uniform', 2 * STEPS)} SELECT query_id, step FROM (SELECT {ONE} AS query_id, min(t::INTEGER) AS step FROM ch JOIN con USING (component) JOIN m ON m.mention_id = ids[mv] WHERE ok AND gold = (SELECT gold FROM m WHERE mention_id = {ONE})) WHERE step IS NOT NULL",
        "steady_state": f"WITH {SCRIPT}, w AS (SELECT query_id, step, avg(accepted::INT) OVER x AS rate, count(*) OVER x AS n FROM sc WINDOW x AS (PARTITION BY query_id ORDER BY step ROWS 39 PRECEDING)) SELECT query_id::INTEGER AS run_id, min(step) FILTER (n = 40 AND rate <= 0.2) AS step FROM w GROUP BY 1",
        "select_entity": selected(SELECT_STEPS, FIRST[1], FIRST[0]),
        "select_auto": f"""WITH RECURSIVE {base()}, {ALL_OF}, {DIRECTED}
SELECT query_id, mention_id FROM (WITH RECURSIVE mem AS (SELECT query_id AS component, mention_id FROM c WHERE query_id IN (SELECT query_id FROM way WHERE direction = 'expel')), qs AS (SELECT query_id AS component, query_id, query_id AS own FROM way WHERE direction = 'expel'),
{setup('paragraph', features.TWO_WORD_NAMES, True, 'expel')}, {replays.chain('expel', SELECT_STEPS)} SELECT query_id, mention_id FROM ({replays.members_of_queries(SELECT_STEPS - 1)}))
UNION ALL SELECT query_id, mention_id FROM (WITH RECURSIVE mem AS (SELECT query_id AS component, mention_id FROM c WHERE query_id IN (SELECT query_id FROM way WHERE direction <> 'expel')), qs AS (SELECT query_id AS component, query_id, query_id AS own FROM way WHERE direction <> 'expel'),
{setup('paragraph', features.TWO_WORD_NAMES, True)}, {replays.chain('influence_to_query', SELECT_STEPS)} SELECT query_id, mention_id FROM ({replays.members_of_queries(SELECT_STEPS - 1)}))""",
        "canopy_direction": f"WITH {base()}, {ALL_OF}, {influence('paragraph', features.TWO_WORD_NAMES, 'c')}, x AS (SELECT query_id, avg((infl > 0)::INT) AS share FROM infl GROUP BY 1) SELECT query_id, round(share, 9) AS share, CASE WHEN share > 0.5 THEN 'expel' ELSE 'influence_to_query' END AS direction FROM x",
        "warm_start": f"""WITH RECURSIVE {base()}, {ALL_OF}, {FIRST[0]}, {FIRST[1]}, {setup('paragraph', features.TWO_WORD_NAMES, True)}, begun AS (
SELECT * FROM (WITH RECURSIVE {replays.chain('influence_to_query', SELECT_STEPS)} SELECT component, nxt AS lab FROM ch WHERE t = {SELECT_STEPS - 1})),
{replays.chain('influence_to_query', SELECT_STEPS, seed=2, start='begun')}
SELECT query_id, mention_id FROM ({replays.members_of_queries(SELECT_STEPS - 1)})""",
        "join_entities": selected(SELECT_STEPS, merged()[1], merged()[0], quantum=25),
        "join_by_selectivity": selected(SELECT_STEPS, merged()[1], merged()[0], quantum=25, policy="by_selectivity"),
        "select_keywords": by_template("SELECT query_id, mention_id FROM found"),
        "select_sql": by_template("SELECT mention_id, mention FROM found JOIN m USING (mention_id)"),
        "select_udtf": by_template("SELECT mention_id, mention FROM found JOIN m USING (mention_id)", "document", features.SHORT_NAMES, False),
        "select_entity_large": f"""WITH RECURSIVE {base(f"m AS MATERIALIZED ({fixtures.line_sql('duckdb')})", LARGE_SHARED, 1)}, {ALL_OF}, {FIRST[0]}, {FIRST[1]}, {setup('document', features.SPECS, True)}, {replays.chain('influence_to_query', LARGE_STEPS)}
{TRACE}""",
        "resolve_all": f"""WITH RECURSIVE m AS MATERIALIZED ({fixtures.customer_sql('duckdb')}), bl AS (SELECT mention_id, min(mention_id) OVER (PARTITION BY regexp_extract(mention, '([0-9]{{8}})', 1)) AS component, count(*) OVER (PARTITION BY regexp_extract(mention, '([0-9]{{8}})', 1)) AS k FROM m),
mem AS (SELECT component, mention_id FROM bl WHERE k > 1), qs AS (SELECT DISTINCT component, component AS query_id, component AS own FROM mem), {model('paragraph', features.SHORT_NAMES, True)}, wts0 AS (SELECT component AS query_id, mention_id, 1.0 AS weight FROM mem), {replays.places()},
{replays.chain('uniform', RESOLVE_STEPS)}
SELECT 0 AS run_id, ids[z] AS mention_id, ids[nxt[z]] AS entity_id FROM (SELECT *, unnest(range(1, n + 1)) AS z FROM ch JOIN con USING (component) WHERE t = {RESOLVE_STEPS - 1}) UNION ALL SELECT 0, mention_id, mention_id FROM bl WHERE k = 1""",
        "chain_idle": f"""WITH RECURSIVE {base()}, {ALL_OF}, {EACH[0]}, {EACH[1]}, {setup('paragraph', features.TWO_WORD_NAMES, False)}, {replays.chain('influence_to_query', 4000, idle=200)}
SELECT component AS query_id, count(*) AS proposals, count(*) FILTER (ok) AS accepted FROM ch WHERE t >= 0 GROUP BY 1""",
        "salient_terms": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, tm AS (SELECT mention_id, gold, unnest(list_distinct(document)) AS term FROM c1 JOIN m USING (mention_id)), l AS (SELECT term, count(*) FILTER (gold = g) - count(*) FILTER (gold <> g) AS lift FROM tm, (SELECT gold AS g FROM m WHERE mention_id = {ONE}) GROUP BY 1)
SELECT {ONE} AS query_id, term, lift FROM l ORDER BY lift DESC, term LIMIT 3""",
        "move_delta_on_demand": f"""WITH {base()}, {ALL_OF}, {OF_ONE}, {states('c1')}, mem AS (SELECT query_id AS component, mention_id FROM c1), {model('document', features.SPECS, True)},
r AS (SELECT mention_id, entity_id FROM st WHERE how = 'random'), b AS (SELECT i AS x, j AS y, w FROM pw WHERE i <> j UNION ALL SELECT j, i, w FROM pw WHERE i <> j), t AS (SELECT DISTINCT entity_id AS entity_to FROM r)
SELECT r.mention_id, r.entity_id AS entity_from, entity_to, CASE WHEN r.entity_id = entity_to THEN 0 ELSE
  (SELECT coalesce(sum(CASE WHEN o.entity_id = t.entity_to THEN w WHEN o.entity_id = r.entity_id THEN -w ELSE 0 END), 0) FROM b JOIN r o ON o.mention_id = b.y WHERE b.x = r.mention_id) END::BIGINT AS delta FROM r, t""",
        "alias_presample": f"""WITH RECURSIVE {base()}, {influence()}, {DECAY}, {ALIASES}, u AS (SELECT *, {h("'1|' || query_id || '|' || draw || '|a'")} AS a, {h("'1|' || query_id || '|' || draw || '|b'")} AS b FROM tabs, range(1, 51) AS r(draw)),
k AS (SELECT *, least(floor(a / 4294967296.0 * len(ids))::BIGINT, len(ids) - 1) + 1 AS i FROM u) SELECT query_id, draw::INTEGER AS draw, ids[CASE WHEN b / 4294967296.0 < pr[i] THEN i ELSE al[i] END] AS mention_id FROM k""",
        "bsp_proposals": f"WITH RECURSIVE {parallel_setup()}, {replays.proposals(0, BSP_WORKERS, 'wl', 'st0')} SELECT query_id, n, mention_id, entity_from, entity_to FROM pr0",
        "bsp_rounds": f"WITH RECURSIVE {parallel_setup()}, {replays.rounds(BSP_ROUNDS, BSP_WORKERS, 'wl')} SELECT mention_id, entity_id FROM st{BSP_ROUNDS}",
        "bsp_merge_round": f"""WITH RECURSIVE {parallel_setup()}, as0 AS (SELECT query_id, n FROM wl, range(1, {BSP_WORKERS + 1}) AS r(n)), {replays.drawn_mentions(0, 'as0', 'st0', 'wl')}, ask AS (SELECT DISTINCT mention_id, entity_from, entity_to FROM pr0),
{replays.better('ask', 'st0', 'gd')}, bst AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY mention_id ORDER BY delta DESC, entity_to) AS k FROM gd) WHERE k = 1),
mvd AS MATERIALIZED (SELECT s.mention_id, coalesce(g.entity_to, s.entity_id) AS entity_id FROM st0 s LEFT JOIN bst g USING (mention_id)), back AS (SELECT b.mention_id, s.entity_id AS entity_from, -b.mention_id - 1 AS entity_to FROM bst b JOIN mvd s USING (mention_id)),
{replays.better('back', 'mvd', 'alone')}, {replays.applied('alone', 'mvd', 'fin')} SELECT mention_id, entity_id FROM fin""",
        "vector_blocks": f"WITH {vector_planes(12)} SELECT block, mention_id FROM blocks",
        "document_mentions": r"""WITH s AS (SELECT doc_id, list_filter(list_transform(regexp_split_to_array(text, '[.\n]'), lambda x: trim(x, ' ')), lambda x: x <> '') AS ss FROM documents),
l AS (SELECT doc_id, list_filter(ss, lambda x: length(x) = list_max(list_transform(ss, lambda y: length(y))))[1] AS sentence FROM s)
SELECT doc_id AS mention_id, array_to_string(string_split(sentence, ' ')[1:6], ' ') AS mention FROM l WHERE sentence IS NOT NULL""",
        "page_mentions": r"""WITH t AS (SELECT page_id, trim(regexp_extract(html, '(?is)<title>(.*?)</title>', 1), ' ') AS title FROM pages) SELECT page_id AS mention_id, title AS mention, lower(regexp_replace(title, '\s+', ' ', 'g')) AS gold FROM t""",
        "conversation_mentions": "SELECT conv_id * 1000 + turn AS mention_id, array_to_string(string_split(text, ' ')[1:6], ' ') AS mention, conv_id::VARCHAR AS gold FROM conversations",
        "stream_canopy": f"WITH {HANDLES} SELECT query_id, count(*) AS n_mentions FROM hm GROUP BY 1",
        "stream_windows": f"WITH {HANDLES} SELECT strftime(time_bucket(INTERVAL 7 DAY, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d') AS start, query_id, count(*) AS n_mentions FROM hm GROUP BY 1, 2",
        "stream_sessions": """WITH e AS (SELECT user_id AS doc_id, ts, CASE WHEN ts - lag(ts) OVER w > INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
k AS (SELECT doc_id, ts, sum(fresh) OVER (PARTITION BY doc_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, doc_id, count(*) AS n FROM k GROUP BY doc_id, k HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)""",
        "w1_real_time": f"""WITH RECURSIVE {designed(f"m AS MATERIALIZED ({fixtures.line_sql('duckdb')})", SAME, [(round(n * f / (2 - f)), n) for n, f in ((103, 0.65), (226, 0.92), (1302, 0.97))])}, {setup('paragraph', features.TWO_WORD_NAMES, True, 'expel', canopy='d')},
{replays.chain('expel', 500, runs=6)}, {replays.accuracy()}, sz AS (SELECT component, count(*) AS canopy FROM mem GROUP BY 1)
SELECT component AS query_id, canopy, round(avg(f1q) FILTER (t = -1), 9) AS f1_start, round(avg(f1q) FILTER (t = 49), 9) AS f1_50, round(avg(f1q) FILTER (t = 499), 9) AS f1_500 FROM f JOIN sz USING (component) GROUP BY 1, 2""",
        "w2_samplers": " UNION ALL ".join(compared(k, fixtures.INFORMATIVE, SAME) for k in ("uniform", "pin_target", "influence_both", "influence_to_query")),
        "w2_uninformative": " UNION ALL ".join(compared(k, 0, WITHOUT_TOPICS) for k in ("uniform", "pin_target", "influence_both", "influence_to_query")),
        "w5_context": " UNION ALL ".join(in_context(*c) for c in (("none", "none", False, "paragraph"), ("paragraph", "paragraph", False, "paragraph"), ("document", "document", False, "document"), ("paragraph+keywords", "paragraph", True, "paragraph"), ("document+keywords", "document", True, "document"))),
        "w7_worked_example": " UNION ALL ".join(worked(k) for k in ("uniform", "pin_target", "influence_both", "influence_to_query", "expel", "expel_both")),
        "w11_negative_control": f"""WITH {vector_planes(6)}, v AS (SELECT b.mention_id, block, label::VARCHAR AS gold FROM blocks b JOIN embeddings ON vec_id = b.mention_id),
o AS (SELECT mention_id, row_number() OVER (ORDER BY mention_id) AS a FROM v), p AS (SELECT gold, row_number() OVER (ORDER BY {h('mention_id::VARCHAR')}, mention_id) AS a FROM v),
k AS (SELECT 'labels' AS what, block, gold FROM v UNION ALL SELECT 'shuffled labels', block, p.gold FROM v JOIN o USING (mention_id) JOIN p USING (a)),
n AS (SELECT what, count(*) OVER (PARTITION BY what, block, gold) AS b, count(*) OVER (PARTITION BY what, block) AS e, count(*) OVER (PARTITION BY what, gold) AS g FROM k), q AS (SELECT what, avg(b / e) AS p, avg(b / g) AS r FROM n GROUP BY 1)
SELECT what, round(p, 9) AS precision, round(r, 9) AS recall, round(2 * p * r / (p + r), 9) AS f1 FROM q""",
        "w12_stream": f"WITH {HANDLES}, k AS (SELECT query_id, count(*) AS n FROM hm GROUP BY 1) SELECT query_id, n AS streamed, n AS batch FROM k",
    }
    out["alias_spilled"] = out["alias_mass"]
    chains = {f"chain_{s}": chain_key(s) for s in ("uniform", "pin_target", "influence_both", "influence_to_query", "expel", "expel_both")}
    return out | chains | {"chain_alias": chain_key("influence_to_query", draw="alias"), "chain_mh": chain_key("influence_to_query", temperature=30.0)}
