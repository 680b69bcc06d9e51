"""SQL of the registered queries for another engine over the same tables."""

from __future__ import annotations

from linkcluster.sources import fixtures

GEO = fixtures.geo_sql()
# types after harmonisation, sorted and joined
TYPES = "CASE WHEN raw_type IS NULL THEN '' WHEN raw_type = 'settlement|harbour' THEN 'harbour|settlement' WHEN raw_type = 'island' THEN 'island' ELSE 'settlement' END"
V = f"v AS (SELECT *, {TYPES} AS types FROM ({GEO}))"
GOLD = "gold AS (SELECT a.id AS src, b.id AS dst, a.source AS s1, b.source AS s2, a.label AS x, b.label AS y, a.lat AS lat1, a.lon AS lon1, b.lat AS lat2, b.lon AS lon2 FROM v a JOIN v b ON a.gold = b.gold AND a.id < b.id)"
CURATED = "curated AS (SELECT src, dst FROM gold WHERE least(s1, s2) = 'A')"
LEV = "(CASE WHEN greatest(length(x), length(y)) = 0 THEN 1.0::DOUBLE ELSE 1 - levenshtein(x, y)::DOUBLE / greatest(length(x), length(y)) END)"
JW = "jaro_winkler_similarity(x, y)"
HAV = "2 * 6371.0088::DOUBLE * asin(sqrt(least(1.0::DOUBLE, pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2))))"
GEOSIM = f"(CASE WHEN {HAV} <= 1358 THEN 1 - {HAV} / 1358 END)"


def r6(x: str, digits: int = 6) -> str:
    return f"floor(({x}) * 1e{digits}::DOUBLE + 0.5) / 1e{digits}::DOUBLE"


def g9(x: str) -> str:
    return f"floor(({x}) * 1e9::DOUBLE + 0.5)::BIGINT"


def _exhaustive(config: str) -> str:
    cross = "p AS (SELECT a.id AS src, b.id AS dst, a.label AS x, b.label AS y, a.lat AS lat1, a.lon AS lon1, b.lat AS lat2, b.lon AS lon2 FROM v a JOIN v b ON a.id < b.id AND a.source <> b.source)"
    sim = JW if config == "config1" else f"({JW} + {GEOSIM}) / 2"
    bound = {"config1": 0.9, "config2": 0.85, "config3": 0.9}[config]
    return f"WITH {V}, {cross}, links AS (SELECT src, dst, {sim} AS sim FROM p WHERE {sim} >= {bound}::DOUBLE)"


def _links(config: str) -> str:
    return f"{_exhaustive(config)} SELECT src, dst, {r6('sim')} AS sim FROM links"


SCORES = "SELECT n_true, n_pred, n_gold, CASE WHEN n_pred > 0 THEN {p} END AS precision, CASE WHEN n_gold > 0 THEN {r} END AS recall, CASE WHEN n_pred + n_gold > 0 THEN {f} END AS f1".format(
    p=r6("n_true::DOUBLE / n_pred::DOUBLE"), r=r6("n_true::DOUBLE / n_gold::DOUBLE"), f=r6("(2 * n_true)::DOUBLE / (n_pred + n_gold)::DOUBLE")
)


def _input_quality(config: str) -> str:
    return f"{_exhaustive(config)}, {GOLD}, n AS (SELECT (SELECT count(*) FROM links JOIN gold USING (src, dst)) AS n_true, (SELECT count(*) FROM links) AS n_pred, (SELECT count(*) FROM gold) AS n_gold) {SCORES} FROM n"


def _best(mode: str) -> str:
    near = f"near AS (SELECT a.id AS src, b.id AS dst, a.source AS s1, b.source AS s2, a.label AS x, b.label AS y FROM v a JOIN v b ON substr(a.label, 1, 3) = substr(b.label, 1, 3) AND a.id < b.id AND a.source <> b.source)"
    keep = {"mutual": "a = 1 AND b = 1", "either": "a = 1 OR b = 1", "one_sided": "a = 1"}[mode]
    return (
        f"WITH {V}, {near}, e AS (SELECT *, {LEV} AS sim FROM near), w AS (SELECT *, row_number() OVER (PARTITION BY src, s2 ORDER BY {g9('sim')} DESC, dst) AS a, row_number() OVER (PARTITION BY dst, s1 ORDER BY {g9('sim')} DESC, src) AS b FROM e) "
        f"SELECT src, dst, {r6('sim')} AS sim FROM w WHERE {keep}"
    )


#: Components as transitive closure towards smaller ids.
def _components(links: str, p: str = "") -> str:
    return f"{p}e AS (SELECT src AS a, dst AS b FROM ({links}) UNION SELECT dst, src FROM ({links})), {p}c(id, cid) AS (SELECT id, id FROM v UNION SELECT {p}e.b, {p}c.cid FROM {p}c JOIN {p}e ON {p}c.id = {p}e.a), {p}comp AS (SELECT id, min(cid) AS cid FROM {p}c GROUP BY id)"


COMPONENTS = f"WITH RECURSIVE {V}, {GOLD}, {CURATED}, {_components('SELECT src, dst FROM curated')}"
# the initial clusters that later steps start from: config 3 links and the curated ones
CROSS3 = "p AS (SELECT a.id AS src, b.id AS dst, a.label AS x, b.label AS y, a.lat AS lat1, a.lon AS lon1, b.lat AS lat2, b.lon AS lon2 FROM v a JOIN v b ON a.id < b.id AND a.source <> b.source)"
LINKS3 = f"links AS MATERIALIZED (SELECT src, dst FROM p WHERE ({JW} + {GEOSIM}) / 2 >= 0.9::DOUBLE UNION SELECT src, dst FROM curated)"
INITIAL = f"WITH RECURSIVE {V}, {GOLD}, {CURATED}, {CROSS3}, {LINKS3}, {_components('SELECT src, dst FROM links')}"
PAIRS = "pr AS (SELECT a.cid, a.id AS src, b.id AS dst FROM comp a JOIN comp b ON a.cid = b.cid AND a.id < b.id)"
SCORED = f"sc AS (SELECT pr.cid, src, dst, {g9(LEV)} AS g FROM pr JOIN (SELECT id AS src, label AS x FROM v) USING (src) JOIN (SELECT id AS dst, label AS y FROM v) USING (dst))"
# settlement and harbour overlap, islands stand apart; an untyped entity follows its best typed neighbour
GROUPS = (
    "ty AS (SELECT comp.id, comp.cid, CASE WHEN types = '' THEN NULL ELSE min(comp.id) OVER (PARTITION BY comp.cid, types = '', types = 'island') END AS t FROM comp JOIN v ON comp.id = v.id), "
    "ends AS (SELECT src AS u, dst AS w, g FROM sc UNION ALL SELECT dst, src, g FROM sc), "
    "offers AS (SELECT u, arg_max(t, g * 1000000000::HUGEINT - t) AS o FROM ends JOIN ty ON ty.id = w WHERE t IS NOT NULL GROUP BY u), "
    "nw AS (SELECT ty.id, ty.cid, coalesce(t, o, min(CASE WHEN t IS NULL AND o IS NULL THEN ty.id END) OVER (PARTITION BY ty.cid)) AS k FROM ty LEFT JOIN offers ON ty.id = u), "
    "grp AS (SELECT id, min(id) OVER (PARTITION BY k) AS cid FROM nw)"
)
DECOMPOSED = f"{INITIAL}, {PAIRS}, {SCORED}, {GROUPS}, ed AS (SELECT a.cid, src, dst, g FROM sc JOIN grp a ON a.id = src JOIN grp b ON b.id = dst WHERE a.cid = b.cid), en AS MATERIALIZED (SELECT cid, src AS i, dst AS j, g FROM ed UNION ALL SELECT cid, dst, src, g FROM ed)"
# one member leaves each cluster in a round: (round, cid, list of removed)
REFINED = (
    "rf(n, cid, gone) AS (SELECT 0, cid, []::BIGINT[] FROM (SELECT DISTINCT cid FROM en) UNION ALL "
    "SELECT n + 1, cid, list_append(gone, arg_min(i, lo)) FROM (SELECT n, cid, gone, i, row(avg_g, -i) AS lo, avg_g FROM (SELECT rf.n, rf.cid, rf.gone, en.i, sum(g)::DOUBLE / count(*) AS avg_g FROM rf JOIN en ON rf.cid = en.cid "
    "WHERE NOT list_contains(gone, i) AND NOT list_contains(gone, j) GROUP BY rf.n, rf.cid, rf.gone, en.i)) GROUP BY n, cid, gone HAVING min(avg_g) < 0.7::DOUBLE * 1e9::DOUBLE), "
    "out_ AS (SELECT DISTINCT unnest(gone) AS id FROM rf), rfd AS (SELECT grp.id, CASE WHEN out_.id IS NOT NULL THEN grp.id ELSE min(CASE WHEN out_.id IS NULL THEN grp.id END) OVER (PARTITION BY cid) END AS cid FROM grp LEFT JOIN out_ USING (id))"
)
def _reps(order: str, place: str | None = None, base: str = "rfd", p: str = "", extra: str = "") -> str:
    """Representatives of ``base``: the label by ``order``, the position by ``place`` (``mean``: of all), both over members."""
    spot = lambda c: f"avg({c})" if place == "mean" else f"first({c} ORDER BY lat IS NULL, {place or order})"
    return (
        f"{p}lab AS (SELECT {base}.cid, {base}.id, label, types, source, lat, lon, count(*) OVER (PARTITION BY {base}.cid, label) AS often {extra} FROM {base} JOIN v USING (id)), "
        f"{p}tys AS (SELECT cid, string_agg(t, '|' ORDER BY t) AS types FROM (SELECT DISTINCT cid, unnest(string_split(types, '|')) AS t FROM {p}lab WHERE types <> '') GROUP BY cid), "
        f"{p}srcs AS (SELECT cid, string_agg(source, '|' ORDER BY source) AS sources FROM (SELECT DISTINCT cid, source FROM {p}lab) GROUP BY cid), "
        f"{p}rep AS (SELECT lab.cid, first(label ORDER BY {order}) AS label, any_value(coalesce(tys.types, '')) AS types, any_value(srcs.sources) AS sources, "
        f"string_agg(id::VARCHAR, '|' ORDER BY id) AS members, count(*)::INT AS n, {spot('lat')} AS lat, {spot('lon')} AS lon FROM {p}lab lab LEFT JOIN {p}tys tys ON lab.cid = tys.cid JOIN {p}srcs srcs ON lab.cid = srcs.cid GROUP BY lab.cid)"
    )


BY_FREQ = "often DESC, length(label) DESC, id"
REP_FREQ = _reps(BY_FREQ)


def _flat(p: str = "") -> str:
    return f"SELECT cid, label, types, sources, members, n, {r6('lat')} AS lat, {r6('lon')} AS lon FROM {p}rep"


FLAT = _flat()


def label_geo(a: str, b: str) -> str:
    """Mean of label and position similarity; without a position on either side that of the labels."""
    geo = GEOSIM
    for x, y in (("lat1", f"{a}.lat"), ("lon1", f"{a}.lon"), ("lat2", f"{b}.lat"), ("lon2", f"{b}.lon")):
        geo = geo.replace(x, y)
    jw = f"jaro_winkler_similarity({a}.label, {b}.label)"
    return f"(CASE WHEN {a}.lat IS NOT NULL AND {b}.lat IS NOT NULL THEN 0.5::DOUBLE * {jw} + 0.5::DOUBLE * coalesce({geo}, 0::DOUBLE) ELSE {jw} END)"


def _candidates(sim: str, theta: float, block: str, meet: str) -> str:
    """Compatible pairs of representatives a and b that ``meet``, of that similarity at least."""
    over = "list_has_any(string_split({0}, '|'), string_split({1}, '|'))"
    return (
        f"cand AS MATERIALIZED (SELECT {block} AS block, a.cid AS l, b.cid AS r, {g9(sim)} AS g FROM rep a JOIN rep b ON {meet} AND a.cid < b.cid "
        f"AND (a.types = '' OR b.types = '' OR {over.format('a.types', 'b.types')}) AND NOT {over.format('a.sources', 'b.sources')} "
        f"AND len(string_split(a.sources, '|')) + len(string_split(b.sources, '|')) <= 4 AND a.n + b.n <= 4 WHERE {g9(sim)} >= {int(theta * 1e9)})"
    )


LEV_REPS = LEV.replace("(x", "(a.label").replace(" x", " a.label").replace("y)", "b.label)").replace(" y", " b.label")
SAME_BLOCK = "substr(a.label, 1, 3) = substr(b.label, 1, 3)"
#: Triplets of a block in their order; each joins its two clusters if these are still compatible.
MERGED = (
    "ranked AS MATERIALIZED (SELECT block, l, r, row_number() OVER (PARTITION BY block ORDER BY g DESC, l, r) AS i FROM cand), "
    "mg(block, i, st) AS (SELECT block, 0::BIGINT, list({'root': cid, 'm': [cid], 's': string_split(sources, '|'), 'n': n}) FROM (SELECT block, l AS cid FROM cand UNION SELECT block, r FROM cand) JOIN rep USING (cid) GROUP BY block "
    "UNION ALL SELECT block, i + 1, CASE WHEN a.root <> b.root AND NOT list_has_any(a.s, b.s) AND len(a.s) + len(b.s) <= 4 AND a.n + b.n <= 4 "
    "THEN list_append(list_filter(st, lambda x: x.root <> a.root AND x.root <> b.root), {'root': least(a.root, b.root), 'm': list_concat(a.m, b.m), 's': list_concat(a.s, b.s), 'n': a.n + b.n}) ELSE st END "
    "FROM (SELECT mg.block, mg.i, st, list_filter(st, lambda x: list_contains(x.m, k.l))[1] AS a, list_filter(st, lambda x: list_contains(x.m, k.r))[1] AS b FROM mg JOIN ranked k ON k.block = mg.block AND k.i = mg.i + 1)), "
    "mv AS (SELECT unnest(c.m) AS cid, c.root AS root FROM (SELECT unnest(st) AS c FROM (SELECT block, arg_max(st, i) AS st FROM mg GROUP BY block))), "
    "fin AS (SELECT id, coalesce(root, rfd.cid) AS cid FROM rfd LEFT JOIN mv ON rfd.cid = mv.cid)"
)
#: All members under the bound at once.
BULK = (
    "low AS (SELECT i AS id FROM (SELECT cid, i, sum(g)::DOUBLE / count(*) AS avg_g FROM en GROUP BY cid, i) WHERE avg_g < 0.7::DOUBLE * 1e9::DOUBLE), "
    "rfd AS (SELECT grp.id, CASE WHEN low.id IS NOT NULL THEN grp.id ELSE min(CASE WHEN low.id IS NULL THEN grp.id END) OVER (PARTITION BY cid) END AS cid FROM grp LEFT JOIN low ON grp.id = low.id)"
)
EDGES = "ed AS (SELECT a.cid, src, dst, g FROM sc JOIN grp a ON a.id = src JOIN grp b ON b.id = dst WHERE a.cid = b.cid), en AS MATERIALIZED (SELECT cid, src AS i, dst AS j, g FROM ed UNION ALL SELECT cid, dst, src, g FROM ed)"


def _workflow(links: str, types: bool = True, refine: bool = True, merge: bool = True, blocking: bool = True) -> str:
    """The whole workflow on the pairs of ``links`` as table expressions, up to ``fin`` (id, cid)."""
    scored = f"e1 AS MATERIALIZED (SELECT src, dst, a.source AS s1, b.source AS s2, {g9(label_geo('a', 'b'))} AS g FROM ({links}) JOIN v a ON a.id = src JOIN v b ON b.id = dst WHERE a.source <> b.source)"
    best = "e2 AS MATERIALIZED (SELECT src, dst FROM e1 QUALIFY row_number() OVER (PARTITION BY src, s2 ORDER BY g DESC, dst) = 1 AND row_number() OVER (PARTITION BY dst, s1 ORDER BY g DESC, src) = 1)"
    pairs = f"sc AS MATERIALIZED (SELECT pr.cid, src, dst, {g9(label_geo('a', 'b'))} AS g FROM pr JOIN v a ON a.id = src JOIN v b ON b.id = dst)"
    parts = [scored, best, _components("SELECT src, dst FROM e2"), PAIRS, pairs, GROUPS if types else "grp AS (SELECT id, cid FROM comp)", EDGES, REFINED if refine else "rfd AS (SELECT id, cid FROM grp)"]
    if merge:
        meet = SAME_BLOCK if blocking else "true"
        parts += [REP_FREQ, _candidates(label_geo("a", "b"), 0.8, "substr(a.label, 1, 3)" if blocking else "''", meet), MERGED]
    else:
        parts.append("fin AS (SELECT id, cid FROM rfd)")
    return ", ".join(parts)


def _cluster_counts(assign: str) -> str:
    """(n_true, n_pred, n_gold) of a clustering against the gold clusters, from overlap counts."""
    pairs = "coalesce(sum(c * (c - 1) // 2), 0)::BIGINT"
    return (
        f"SELECT (SELECT {pairs} FROM (SELECT count(*) AS c FROM {assign} a JOIN v ON a.id = v.id GROUP BY a.cid, v.gold)) AS n_true, (SELECT {pairs} FROM (SELECT count(*) AS c FROM {assign} GROUP BY cid)) AS n_pred, "
        f"(SELECT {pairs} FROM (SELECT count(*) AS c FROM v GROUP BY gold)) AS n_gold"
    )


def _link_counts(links: str) -> str:
    return f"SELECT (SELECT count(*) FROM {links} JOIN gold USING (src, dst)) AS n_true, (SELECT count(*) FROM {links}) AS n_pred, (SELECT count(*) FROM gold) AS n_gold"


def _rows(**counts: str) -> str:
    """One row of scores for each method."""
    return " UNION ALL ".join(f"SELECT '{m}' AS method, * FROM ({SCORES} FROM ({c}))" for m, c in counts.items())


def _star(p: str, order: str) -> str:
    """Greedy cover of each component of ``links`` (src, dst, sim), vertices in the order of their rank: ``{p}star`` (center, id)."""
    rank = "count(*)::DOUBLE" if order == "degree" else f"sum({g9('sim')})::DOUBLE / count(*)"
    return (
        f"{p}nb AS MATERIALIZED (SELECT u, list(w) AS near, {rank} AS rank FROM (SELECT src AS u, dst AS w, sim FROM links UNION ALL SELECT dst, src, sim FROM links) GROUP BY u), "
        f"{p}ord AS MATERIALIZED (SELECT cid, u, near, row_number() OVER (PARTITION BY cid ORDER BY rank DESC, u) AS i FROM {p}nb JOIN kcomp ON kcomp.id = u), "
        f"{p}cov(cid, i, covered, centers) AS (SELECT DISTINCT cid, 0::BIGINT, []::BIGINT[], []::BIGINT[] FROM {p}ord UNION ALL SELECT o.cid, o.i, CASE WHEN list_contains(covered, u) THEN covered ELSE list_append(list_concat(covered, near), u) END, "
        f"CASE WHEN list_contains(covered, u) THEN centers ELSE list_append(centers, u) END FROM {p}cov c JOIN {p}ord o ON o.cid = c.cid AND o.i = c.i + 1), "
        f"{p}cen AS (SELECT unnest(centers) AS center FROM (SELECT arg_max(centers, i) AS centers FROM {p}cov GROUP BY cid)), "
        f"{p}star AS (SELECT center, unnest(list_append(near, center)) AS id FROM {p}cen JOIN {p}nb ON u = center UNION ALL SELECT id, id FROM v WHERE id NOT IN (SELECT u FROM {p}nb)), "
        f"{p}pairs AS (SELECT DISTINCT a.id AS src, b.id AS dst FROM {p}star a JOIN {p}star b ON a.center = b.center AND a.id < b.id)"
    )


def _found(config: str) -> str:
    """Entities, gold links, the links of a configuration, their components and both stars."""
    return f"{_exhaustive(config).replace('WITH ', 'WITH RECURSIVE ', 1).replace('links AS (', 'links AS MATERIALIZED (')}, {GOLD}, {_components('SELECT src, dst FROM links', 'k')}, {_star('s1', 'degree')}, {_star('s2', 'mean_similarity')}"


def _compare(config: str) -> str:
    rows = _rows(input=_link_counts("links"), star1=_link_counts("s1pairs"), star2=_link_counts("s2pairs"), components=_cluster_counts("kcomp"), workflow=_cluster_counts("fin"))
    return f"{_found(config)}, {_workflow('SELECT src, dst FROM links')} {rows}"


CURATED_RUN = f"WITH RECURSIVE {V}, {GOLD}, {CURATED}"


def _curated(**flags) -> str:
    return f"{CURATED_RUN}, {_workflow('SELECT src, dst FROM curated', **flags)}"


CANDIDATES = _candidates(LEV_REPS, 0.7, "substr(a.label, 1, 3)", SAME_BLOCK)
MEDOID = f"ins AS (SELECT a.cid, src, dst, g FROM ed JOIN rfd a ON a.id = src JOIN rfd b ON b.id = dst WHERE a.cid = b.cid), asim AS (SELECT id, sum(g)::DOUBLE / count(*) / 1e9::DOUBLE AS asim FROM (SELECT src AS id, g FROM ins UNION ALL SELECT dst, g FROM ins) GROUP BY id), {_reps('coalesce((SELECT asim FROM asim WHERE asim.id = lab.id), -1.0) DESC, id')}"
KEYS = _candidates(LEV_REPS, 0.7, "''", f"({SAME_BLOCK} OR right(a.label, 3) = right(b.label, 3))")
CAND_ROWS = f"SELECT block, l, r, {r6('g / 1e9::DOUBLE')} AS sim FROM cand"


def _music(name: str) -> str:
    return f"({fixtures.music_sql(name)})"


def _overview(rows: str) -> str:
    return f"SELECT (SELECT count(*) FROM {rows}) AS entities, (SELECT count(DISTINCT source) FROM {rows}) AS sources, (SELECT sum(c * (c - 1) // 2)::BIGINT FROM (SELECT count(*) AS c FROM {rows} GROUP BY gold)) AS links, (SELECT count(DISTINCT gold) FROM {rows}) AS clusters"


Q3 = "list_distinct(list_transform(generate_series(1, length({c}) - 2), lambda i: substr({c}, i, 3)))"
QA, QB = (f"(CASE WHEN length({c}) < 3 THEN [{c}] ELSE {Q3.format(c=c)} END)" for c in "xy")
INTER = f"len(list_intersect({QA}, {QB}))"


def _soft(values: str, theta: float = 0.9) -> str:
    one = lambda t: f"(SELECT va, vb, sum(part) AS s FROM (SELECT va, vb, {t}, arg_max(part, row(inner_, part)) AS part FROM hits GROUP BY ALL) GROUP BY va, vb)"
    return (
        f"WITH vals AS ({values}), tok AS (SELECT vid, token, count(*) AS tf FROM (SELECT vid, unnest(string_split_regex(lower(value), '[^\\p{{L}}\\p{{N}}]+')) AS token FROM vals) WHERE token <> '' GROUP BY ALL), "
        "df AS (SELECT token, count(*) AS df FROM tok GROUP BY token), raw AS (SELECT vid, token, (1 + ln(tf)) * ln(1 + (SELECT count(*) FROM vals)::DOUBLE / df) AS raw FROM tok JOIN df USING (token)), "
        "w AS (SELECT vid, token, raw / sqrt(sum(raw * raw) OVER (PARTITION BY vid)) AS w FROM raw), "
        f"close_ AS (SELECT a.token AS ta, b.token AS tb, CASE WHEN a.token = b.token THEN 1.0::DOUBLE ELSE jaro_winkler_similarity(least(a.token, b.token), greatest(a.token, b.token)) END AS inner_ FROM df a, df b WHERE a.token = b.token OR jaro_winkler_similarity(least(a.token, b.token), greatest(a.token, b.token)) >= {theta}), "
        "hits AS (SELECT a.vid AS va, b.vid AS vb, ta, tb, inner_, a.w * b.w * inner_ AS part FROM w a JOIN close_ ON a.token = ta JOIN w b ON b.token = tb WHERE a.vid < b.vid) "
        f"SELECT va, vb, {r6('least(1.0::DOUBLE, greatest(x.s, y.s))')} AS sim FROM {one('ta')} x JOIN {one('tb')} y USING (va, vb)"
    )


def _mixed(links: str, fifth: bool = False) -> str:
    """The whole workflow on links of configurations 1 and 3; a cluster holds one entity of each source at most."""
    sql = f"{_exhaustive('config1').replace('WITH ', 'WITH RECURSIVE ', 1).replace('links AS (SELECT src, dst, ', 'links AS MATERIALIZED (SELECT src, dst, ')}, {GOLD}, l3 AS MATERIALIZED (SELECT src, dst FROM p WHERE ({JW} + {GEOSIM}) / 2 >= 0.9::DOUBLE), {_workflow(links)}, {_reps(BY_FREQ, base='fin', p='f')} {_flat('f')}"
    return sql.replace(GEO, fixtures.geo_sql(fifth=True)).replace("<= 4", "<= 5") if fifth else sql


def oracle_sql() -> dict[str, str]:
    gold = f"WITH {V}, {GOLD}"
    cost = lambda n: f"SELECT {n} AS letters, count(*) AS blocks, sum(b * (b - 1) // 2)::BIGINT AS comparisons, max(b) AS largest, {r6('1 - sum(b * (b - 1) / 2)::DOUBLE / (sum(b) * (sum(b) - 1) / 2)::DOUBLE')} AS reduction FROM (SELECT count(*) AS b FROM v GROUP BY substr(label, 1, {n}))"
    return {
        "geo_entities": f"SELECT id, gold, source, label, raw_type, {r6('lat')} AS lat, {r6('lon')} AS lon FROM ({GEO})",
        "music_entities": f"SELECT id, gold, source, title, artist, album, year, length FROM {_music('part')}",
        "overview_geo": f"WITH {V} {_overview('v')}",
        "overview_music": " UNION ALL ".join(f"SELECT '{t}' AS \"table\", * FROM (WITH m AS (SELECT * FROM {_music(t)}) {_overview('m')})" for t in ("part", "orders", "lineitem")),
        "source_structure": f"{gold} SELECT source AS s1, source AS s2, count(*) AS n FROM v GROUP BY source UNION ALL SELECT least(s1, s2), greatest(s1, s2), count(*) FROM gold WHERE s1 <> s2 GROUP BY ALL",
        "normalize_year_length": f"SELECT id, 1990 + gold % 30 AS year, 120 + gold % 200 AS seconds FROM {_music('part')}",
        "harmonize_types": f"WITH {V} SELECT id, types FROM v",
        "harmonize_types_table": f"WITH {V} SELECT id, types FROM v",
        "validate_graph": f"{gold}, w AS (SELECT id FROM v WHERE list_contains(string_split(types, '|'), 'settlement')) SELECT (SELECT count(*) FROM v) AS vertices_in, (SELECT count(*) FROM w) AS vertices_out, (SELECT count(*) FROM gold) + 2 * (SELECT count(*) FROM v) AS links_in, (SELECT count(*) FROM gold WHERE src IN (FROM w) AND dst IN (FROM w) AND s1 <> s2) AS links_out",
        "score_links": f"{gold} SELECT src, dst, {r6(JW)} AS sim FROM gold",
        "best_links_mutual": _best("mutual"),
        "best_links_either": _best("either"),
        "best_links_one_sided": _best("one_sided"),
        "string_similarities": f"{gold} SELECT src, dst, {r6(JW)} AS jw, {r6(LEV)} AS lev, {r6(f'{INTER}::DOUBLE / (len({QA}) + len({QB}) - {INTER})')} AS jaccard, {r6(f'2 * {INTER}::DOUBLE / (len({QA}) + len({QB}))')} AS dice, {r6('(x = y)::INT::DOUBLE')} AS same FROM gold",
        "jaro_winkler_expression": f"{gold} SELECT src, dst, {r6(JW)} AS jw FROM gold",
        "geo_similarity": f"{gold} SELECT src, dst, {r6(GEOSIM)} AS sim FROM gold",
        "link_config1": _links("config1"),
        "link_config2": _links("config2"),
        "link_config3": _links("config3"),
        "pairwise_exhaustive": _links("config3"),
        "soft_tfidf_albums": _soft(f"SELECT DISTINCT album AS vid, album AS value FROM {_music('part')} WHERE album IS NOT NULL"),
        "star_links": f"SELECT src, id AS dst FROM (SELECT id, min(id) OVER (PARTITION BY gold) AS src FROM {_music('part')}) WHERE id <> src",
        "curated": f"{gold}, {CURATED} SELECT src, dst FROM curated",
        **{f"components_{m}": f"{COMPONENTS} SELECT id, cid FROM comp" for m in ("minlabel", "stars", "local", "sized", "sql")},
        "intra_pairs": f"{INITIAL}, {PAIRS} SELECT * FROM pr",
        "intra_pairs_cross_source": f"{INITIAL}, {PAIRS} SELECT pr.* FROM pr JOIN v a ON a.id = src JOIN v b ON b.id = dst WHERE a.source <> b.source",
        "intra_scores": f"{INITIAL}, {PAIRS} SELECT cid, src, dst, {r6(JW)} AS sim FROM pr JOIN (SELECT id AS src, label AS x FROM v) USING (src) JOIN (SELECT id AS dst, label AS y FROM v) USING (dst)",
        "type_grouping": f"{INITIAL}, {PAIRS}, {SCORED}, {GROUPS} SELECT id, cid FROM grp",
        "refine_grouped": f"{DECOMPOSED}, {REFINED} SELECT id, cid FROM rfd",
        "refine_rounds": f"{DECOMPOSED}, {REFINED} SELECT id, cid FROM rfd",
        "representatives": f"{DECOMPOSED}, {REFINED}, {REP_FREQ} {FLAT}",
        "representatives_source_priority": f"{DECOMPOSED}, {REFINED}, {_reps('source, id')} {FLAT}",
        "representatives_longest": f"{DECOMPOSED}, {REFINED}, {_reps('length(label) DESC, id', 'mean')} {FLAT}",
        "blocking_cost": f"WITH {V} {' UNION ALL '.join(cost(n) for n in (1, 2, 3, 4))}",
        "block_balance": f"WITH {V}, s AS (SELECT substr(label, 1, 2) AS block, count(*) AS b FROM v GROUP BY 1) SELECT block, b, b * (b - 1) // 2 AS pairs, coalesce(sum(b * (b - 1) // 2) OVER (ORDER BY b * (b - 1) // 2 DESC, block ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS pairs_before FROM s",
        "pair_completeness": f"{gold} SELECT sum((substr(x, 1, 3) = substr(y, 1, 3))::INT)::BIGINT AS met, count(*) AS wanted FROM gold",
        "merge_candidates": f"{DECOMPOSED}, {REFINED}, {REP_FREQ}, {CANDIDATES} {CAND_ROWS}",
        "merge_candidates_tiled": f"{DECOMPOSED}, {REFINED}, {REP_FREQ}, {CANDIDATES} {CAND_ROWS}",
        "merge_candidates_keys": f"{DECOMPOSED}, {REFINED}, {REP_FREQ}, {KEYS} SELECT l, r, {r6('g / 1e9::DOUBLE')} AS sim FROM cand",
        **{f"merge_{m}": f"{DECOMPOSED}, {REFINED}, {REP_FREQ}, {CANDIDATES}, {MERGED} SELECT id, cid FROM fin" for m in ("block_best", "dominant", "auto", "grouped")},
        "refine_bulk": f"{DECOMPOSED}, {BULK} SELECT id, cid FROM rfd",
        "refine_max_rounds": f"{DECOMPOSED}, {REFINED.replace('FROM rf JOIN en ON rf.cid = en.cid ', 'FROM rf JOIN en ON rf.cid = en.cid AND rf.n < 1 ')} SELECT id, cid FROM rfd",
        "representatives_medoid": f"{DECOMPOSED}, {REFINED}, {MEDOID} {FLAT}",
        "workflow_geo": f"{_curated()}, {_reps(BY_FREQ, base='fin', p='f')} {_flat('f')}",
        "quality_curated": f"{_curated()} {_rows(input=_link_counts('curated'), workflow=_cluster_counts('fin'))}",
        "ablation_no_types": f"{_curated(types=False)} {SCORES} FROM ({_cluster_counts('fin')})",
        "ablation_no_refinement": f"{_curated(refine=False)} {SCORES} FROM ({_cluster_counts('fin')})",
        "ablation_no_merge": f"{_curated(merge=False)} {SCORES} FROM ({_cluster_counts('fin')})",
        "ablation_no_blocking": f"{_curated(blocking=False)} {SCORES} FROM ({_cluster_counts('fin')})",
        "link_delta": f"{_curated()}, pred AS (SELECT a.id AS src, b.id AS dst FROM fin a JOIN fin b ON a.cid = b.cid AND a.id < b.id), d AS (SELECT i, p, g FROM (SELECT src, dst, 1 AS i FROM curated) FULL JOIN (SELECT src, dst, 1 AS p FROM pred) USING (src, dst) FULL JOIN (SELECT src, dst, 1 AS g FROM gold) USING (src, dst)) SELECT count(*) FILTER (WHERE i IS NULL AND p = 1 AND g = 1) AS new_correct, count(*) FILTER (WHERE i = 1 AND p IS NULL AND g IS NULL) AS wrong_removed, count(*) FILTER (WHERE i = 1 AND p IS NULL AND g = 1) AS correct_lost, count(*) FILTER (WHERE i IS NULL AND p = 1 AND g IS NULL) AS new_wrong FROM d",
        "star1": f"{_found('config3')} SELECT center, id FROM s1star",
        "star2": f"{_found('config3')} SELECT center, id FROM s2star",
        **{f"best_star{x}": f"{_found(f'config{c}')}, q AS ({_rows(star1=_link_counts('s1pairs'), star2=_link_counts('s2pairs'))}) SELECT arg_max(method, row(f1, method)) AS method, max(f1) AS f1 FROM q" for c, x in ((1, "_config1"), (2, "_config2"), (3, ""))},
        **{f"quality_config{c}": _compare(f"config{c}") for c in (1, 2, 3)},
        "workflow_geo_large": _mixed("SELECT src, dst FROM links UNION SELECT src, dst FROM l3"),
        "workflow_geo_five": _mixed("SELECT src, dst FROM (SELECT src, dst FROM links UNION SELECT src, dst FROM l3) WHERE substr(md5(src::VARCHAR || '-' || dst::VARCHAR), 1, 4) < '6666'", fifth=True),
        "quality_input_config1": _input_quality("config1"),
        "quality_input_config2": _input_quality("config2"),
        "quality_input_config3": _input_quality("config3"),
        "cluster_profile": f"{INITIAL}, s AS (SELECT cid, count(*) AS size, count(DISTINCT source) AS k FROM comp JOIN v USING (id) GROUP BY cid) SELECT size, count(*) AS clusters, sum(size)::BIGINT AS entities, count(*) FILTER (WHERE k < size) AS repeated_sources FROM s GROUP BY size",
        "compactness": f"{COMPONENTS} SELECT count(*) AS clusters, sum(c)::BIGINT AS members, sum(c * (c - 1) // 2)::BIGINT AS links FROM (SELECT count(*) AS c FROM comp GROUP BY cid)",
        "exact_match_rate": f"{COMPONENTS}, s AS (SELECT gold, comp.cid, count(*) OVER (PARTITION BY comp.cid) AS cn FROM comp JOIN v USING (id)), g AS (SELECT gold, count(DISTINCT cid) AS k, max(cn) AS cn, count(*) AS n FROM s GROUP BY gold) SELECT count(*) FILTER (WHERE k = 1 AND cn = n) AS whole, count(*) AS clusters FROM g",
        "running_example": "SELECT * FROM (VALUES (1::BIGINT, 'l1', 't1', 'A|B|C|D', '1|2|5|6', 4::INT), (3::BIGINT, 'l3', 't2', 'C|D', '3|4', 2::INT), (7::BIGINT, 'z7', 't1', 'A', '7', 1::INT)) t(cid, label, types, sources, members, n)",
        "documents_near_copies": (
            "WITH w AS (SELECT doc_id, source, string_split(trim(regexp_replace(lower(text), '[^\\p{L}\\p{N}]+', ' ', 'g')), ' ') AS w FROM documents WHERE text IS NOT NULL), "
            "g AS (SELECT doc_id, source, unnest(list_distinct(list_transform(generate_series(1, len(w) - 2), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]))) AS g FROM w WHERE len(w) >= 3), "
            "s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY 1), k AS (SELECT * FROM g WHERE g IN (SELECT g FROM g GROUP BY g HAVING count(*) > 1)), "
            "p AS (SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS c FROM k a JOIN k b ON a.g = b.g AND a.doc_id < b.doc_id AND a.source <> b.source GROUP BY 1, 2), "
            "q AS (SELECT src, dst, c::DOUBLE / (x.n + y.n - c) AS sim FROM p JOIN s x ON x.doc_id = src JOIN s y ON y.doc_id = dst) "
            f"SELECT src, dst, {r6('sim')} AS sim FROM q WHERE sim >= 0.3"
        ),
        "passage_links": (
            "WITH g AS (SELECT DISTINCT k, id, unnest(list_transform(generate_series(1, len(w) - 4), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] || ' ' || w[i + 4])) AS g FROM "
            "(SELECT k, id, list_filter(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '') AS w FROM (SELECT 'd' AS k, doc_id AS id, text FROM documents UNION ALL SELECT 'b', item_id, text FROM benchmark) WHERE text IS NOT NULL) WHERE len(w) >= 5), "
            "s AS (SELECT id, count(*) AS n FROM g WHERE k = 'b' GROUP BY id), h AS (SELECT a.id AS doc_id, b.id AS item_id, count(*) AS c FROM g a JOIN g b ON a.g = b.g WHERE a.k = 'd' AND b.k = 'b' GROUP BY ALL) "
            f"SELECT doc_id, item_id, {r6('c::DOUBLE / n')} AS sim FROM h JOIN s ON s.id = item_id WHERE 10 * c >= 8 * n"
        ),
        "embedding_links": (
            "WITH p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS sim FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 20 = 0) "
            f"SELECT src, first(dst ORDER BY {g9('sim')} DESC, dst) AS dst, {r6('max(sim)', 4)} AS sim FROM p GROUP BY src"
        ),
        "page_entities": "SELECT regexp_extract(url, '://([^/]+)', 1) AS source, count(*) AS n, min(regexp_extract(html, '<title>([^<]*)</title>', 1)) AS first_label FROM pages GROUP BY 1",
        "uri_dictionary": "SELECT count(DISTINCT url) AS uris, count(DISTINCT url) AS ids FROM pages",
        "geojson": f"WITH {V} SELECT count(*) AS features, count(*) FILTER (WHERE lat IS NOT NULL AND lon IS NOT NULL) AS points FROM v",
        "scan_pruned": "SELECT l_linenumber, count(*) AS n, sum(l_quantity)::DOUBLE AS quantity FROM lineitem WHERE l_shipdate >= DATE '1997-01-01' AND l_quantity < 10 GROUP BY 1",
        "join_hash": "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
        "join_broadcast": "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1",
        "join_outer": "SELECT count(*) AS n_rows, count(*) FILTER (WHERE n IS NULL) AS unsold FROM part FULL JOIN (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1) ON p_partkey = l_partkey",
        "join_semi_anti": "SELECT count(*) FILTER (WHERE c_custkey IN (SELECT o_custkey FROM orders)) AS with_orders, count(*) FILTER (WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)) AS without_orders FROM customer",
        "join_cross": "SELECT r_name, count(*) AS n FROM region, nation GROUP BY 1",
        "join_band": "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal::DOUBLE - b.s_acctbal::DOUBLE) <= 50",
        "join_interval": "SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND floor(epoch(b.ts)) BETWEEN floor(epoch(a.ts)) AND floor(epoch(a.ts)) + 3600 GROUP BY 1",
        "join_asof": "WITH l AS (SELECT l_orderkey % 10 AS g, l_shipdate::DATE AS t FROM lineitem), o AS (SELECT o_orderkey % 10 AS g, o_orderdate::DATE AS u FROM orders) SELECT l.g, count(*) AS n, count(o.u) AS hits, max(date_diff('day', o.u, l.t))::INT AS gap FROM l ASOF LEFT JOIN (SELECT DISTINCT g, u FROM o) o ON l.g = o.g AND l.t >= o.u GROUP BY 1",
        "agg_basic": f"SELECT l_returnflag, sum(l_quantity::DOUBLE) AS total, min(l_quantity::DOUBLE) AS low, max(l_quantity::DOUBLE) AS high, {r6('avg(l_quantity::DOUBLE)')} AS mean, count(*) AS n FROM lineitem GROUP BY 1",
        "agg_best_by": "SELECT p_brand, first(p_partkey ORDER BY p_size DESC, p_partkey) AS p_partkey, max(p_size) AS p_size FROM part GROUP BY 1",
        "agg_gather": "SELECT n_regionkey, string_agg(DISTINCT n_name, '|' ORDER BY n_name) AS names FROM nation GROUP BY 1",
        "agg_distinct": "SELECT event_type, count(DISTINCT user_id) AS n FROM events GROUP BY 1",
        "agg_quantiles": "SELECT lang, quantile_cont(n_chars, 0.25)::DOUBLE AS q1, quantile_cont(n_chars, 0.5)::DOUBLE AS q2, quantile_cont(n_chars, 0.75)::DOUBLE AS q3 FROM documents GROUP BY 1",
        "agg_grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), (o_orderpriority), ())",
        "agg_pivot": "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1",
        "window_ranks": "SELECT p_partkey, p_brand, p_size, row_number() OVER w::INT AS row_number, rank() OVER (PARTITION BY p_brand ORDER BY p_size)::INT AS rank, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size)::INT AS dense_rank, ntile(4) OVER w::INT AS ntile FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)",
        "window_shift": "SELECT event_id, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1)::BIGINT AS previous FROM events",
        "window_running": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate::DATE RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS week FROM orders",
        "topk_per_group": "SELECT p_brand, p_partkey, p_size FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_size DESC, p_partkey) AS n FROM part) WHERE n <= 3",
        "topk_global": "SELECT p_partkey, p_size FROM part ORDER BY p_size DESC, p_partkey LIMIT 10",
        "set_operations": "SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM customer) AS union_all, (SELECT count(*) FROM (SELECT o_custkey FROM orders INTERSECT SELECT c_custkey FROM customer)) AS common, (SELECT count(*) FROM (SELECT c_custkey FROM customer EXCEPT ALL SELECT o_custkey FROM orders)) AS only_right, (SELECT count(*) FROM (SELECT o_custkey FROM orders UNION SELECT c_custkey FROM customer)) AS union_distinct",
        "json_properties": "SELECT event_type, count(*) FILTER (WHERE json_valid(props)) AS with_json, count(*) AS n FROM events GROUP BY 1",
    }
