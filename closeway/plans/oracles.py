"""The same tables in DuckDB SQL: named blocks, put together in the order they need each other."""

from __future__ import annotations

from ..operators import text as T

HEX = "CAST('0x' || substr(md5({c}), {a}, 8) AS BIGINT)"


def _in(words) -> str:
    return ", ".join(f"'{w}'" for w in words)


TAG = f"""CASE WHEN lower({{t}}) IN ({_in(T.PREPOSITIONS)}) THEN 'I' WHEN lower({{t}}) IN ({_in(T.DETERMINERS)}) THEN 'D' WHEN lower({{t}}) IN ({_in(T.AUXILIARIES)}) THEN 'Z'
 WHEN lower({{t}}) IN ({_in(T.PRONOUNS)}) THEN 'P' WHEN lower({{t}}) IN ({_in(T.CONJUNCTIONS)}) THEN 'K' WHEN regexp_matches({{t}}, '^[0-9]+$') THEN 'C'
 WHEN regexp_matches(lower({{t}}), '^[a-z]+ed$') THEN 'E' WHEN regexp_matches(lower({{t}}), '^[a-z]+ing$') THEN 'G' WHEN regexp_matches(lower({{t}}), '^[a-z]+ly$') THEN 'R'
 WHEN regexp_matches(lower({{t}}), '^[a-z]*[a-rt-z]s$') THEN 'Z' ELSE 'N' END"""
PHRASES = "|".join(p.phrase for p in sorted(T.TABLE_LEXICON, key=lambda p: (-len(p.phrase), p.phrase)))
REL = "CASE {c} " + " ".join(f"WHEN '{p.phrase}' THEN {p.rel_id}" for p in T.TABLE_LEXICON) + " END"
SYNTAX = "|".join(f"(?:{p})" for p in T.PATTERNS)
N_REL = len(T.TABLE_LEXICON)
LINE = "sqrt(CAST(({x1} - {x2}) * ({x1} - {x2}) + ({y1} - {y2}) * ({y1} - {y2}) AS DOUBLE))"
TURN = "(CASE WHEN atan2({dy}, {dx}) < 0 THEN atan2({dy}, {dx}) + 2 * pi() ELSE atan2({dy}, {dx}) END)"


def line(a: str, b: str, x: str = "x", y: str = "y") -> str:
    return LINE.format(x1=f"{a}.{x}", x2=f"{b}.{x}", y1=f"{a}.{y}", y2=f"{b}.{y}")


def placed(table: str, key: str, bal: str, nation: str) -> str:
    return f"""SELECT n_regionkey AS city_id, {key} AS key, abs(CAST(round(100 * {bal}) AS BIGINT)) AS cents FROM {table} JOIN nation ON n_nationkey = {nation}"""


def mentions(names: str) -> str:
    return f"SELECT t.doc_id, t.sent_id, t.i AS first, t.name, g.poi_id, g.etype FROM (SELECT doc_id, sent_id, unnest(range(0, len(toks))) AS i, lower(unnest(toks)) AS name FROM tok) t JOIN {names} g ON g.name = t.name"


#: name -> (blocks it needs, SQL). Every block's columns are those of the Spark table of that name.
BLOCKS: dict[str, tuple[tuple[str, ...], str]] = {
    "vw": ((), "SELECT p_partkey % 5 AS city, CAST(ceil(sqrt(count(*))) AS BIGINT) AS w FROM part GROUP BY 1"),
    "v": (("vw",), """SELECT CAST(p_partkey % 5 AS INTEGER) AS city_id, p_partkey // 5 AS vertex_id, (p_partkey // 5) % w AS col, (p_partkey // 5) // w AS row,
      100 * ((p_partkey // 5) % w) + (7 * p_size) % 21 - 10 AS x, 100 * ((p_partkey // 5) // w) + (13 * p_partkey) % 21 - 10 AS y, w, p_partkey FROM part JOIN vw ON vw.city = p_partkey % 5"""),
    "e": (("v",), f"""SELECT a.city_id, 2 * a.vertex_id + d AS edge_id, a.vertex_id AS u, b.vertex_id AS v, CAST(round(10 * {line("a", "b")}) AS BIGINT) AS len_dm
      FROM v a, (VALUES (0), (1)) t(d), v b WHERE b.city_id = a.city_id AND b.vertex_id = a.vertex_id + (CASE WHEN d = 0 THEN 1 ELSE a.w END) AND (d = 1 OR (a.row = b.row AND a.p_partkey % 7 <> 3))"""),
    "mx": (("v",), "SELECT city_id, max(col) AS mc, max(row) AS mr FROM v GROUP BY 1"),
    "poi": (("mx",), f"""SELECT q.city_id, key AS poi_id, (7919 * key + 31 * cents) % (100 * mc) AS x, (104729 * key + 17 * cents) % (100 * mr) AS y FROM ({placed("supplier", "s_suppkey", "s_acctbal", "s_nationkey")}) q JOIN mx ON mx.city_id = q.city_id"""),
    "cust": (("mx",), f"""SELECT q.city_id, key AS poi_id, (7919 * key + 31 * cents) % (100 * mc) AS x, (104729 * key + 17 * cents) % (100 * mr) AS y FROM ({placed("customer", "c_custkey", "c_acctbal", "c_nationkey")}) q JOIN mx ON mx.city_id = q.city_id"""),
    "sn": ((), "SELECT count(*) AS n, min(s_suppkey) AS lo FROM supplier"),
    "word": ((), "SELECT name, count(*) AS docs FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+'))) AS name FROM documents WHERE lang = 'en') WHERE length(name) >= 4 GROUP BY 1 HAVING count(*) >= 3"),
    "gaz": (("word", "sn"), f"""SELECT name, {HEX.format(c="name", a=9)} % n + lo AS poi_id, list_extract(['ORG', 'LOC', 'FAC', 'GPE'], {HEX.format(c="name", a=17)} % 4 + 1) AS etype FROM word, sn WHERE {HEX.format(c="name", a=1)} % 4 = 0"""),
    "known": (("gaz", "word"), f"""SELECT name, poi_id, etype FROM gaz UNION ALL SELECT name, NULL, NULL FROM word WHERE {HEX.format(c="name", a=1)} % 4 = 1 AND {HEX.format(c="name", a=9)} % 25 = 0"""),
    "host": (("mx", "sn"), f"""SELECT q.city_id, key, cents, (7919 * key + 31 * cents) % (100 * mc) AS px, (104729 * key + 17 * cents) % (100 * mr) AS py, mc, mr FROM ({placed("supplier", "s_suppkey", "s_acctbal", "s_nationkey")}) q JOIN mx ON mx.city_id = q.city_id"""),
    "photo": (("host",), """SELECT city_id, event_id AS photo_id, user_id, ts, event_type,
      CASE WHEN event_type IN ('purchase', 'signup') THEN px + (37 * event_id) % 81 - 40 ELSE (7919 * event_id + 31 * cents) % (100 * mc) END AS x,
      CASE WHEN event_type IN ('purchase', 'signup') THEN py + (53 * event_id) % 81 - 40 ELSE (104729 * event_id + 17 * cents) % (100 * mr) END AS y
      FROM events, sn, host WHERE host.key = user_id % sn.n + sn.lo"""),
    "vpop": (("photo", "v"), f"SELECT v.city_id, v.vertex_id, count(*) AS photos FROM photo p JOIN v ON v.city_id = p.city_id AND v.x BETWEEN p.x - 20 AND p.x + 20 AND v.y BETWEEN p.y - 20 AND p.y + 20 WHERE {line('p', 'v')} <= 20 GROUP BY 1, 2"),
    "sent": ((), "SELECT doc_id, sent_id, sentence FROM (SELECT doc_id, unnest(range(0, len(s))) AS sent_id, unnest(s) AS sentence FROM (SELECT doc_id, string_split_regex(text, '[.!?\\n]') AS s FROM documents WHERE lang = 'en')) WHERE regexp_matches(sentence, '[^ ]')"),
    "tok": (("sent",), "SELECT doc_id, sent_id, regexp_extract_all(sentence, '[A-Za-z]+|[0-9]+') AS toks FROM sent"),
    "ment": (("tok", "gaz"), mentions("gaz")),
    "pair": (("ment", "tok"), f"""SELECT doc_id, sent_id, at_i, at_j, pi, pj, lower(array_to_string(g, ' ')) AS gap, array_to_string(list_transform(g, lambda x: {TAG.format(t="x")}), '') AS tags FROM (
      SELECT a.doc_id, a.sent_id, a.first AS at_i, b.first AS at_j, a.poi_id AS pi, b.poi_id AS pj, toks[a.first + 2 : b.first] AS g FROM ment a JOIN ment b ON a.doc_id = b.doc_id AND a.sent_id = b.sent_id AND b.first - a.first - 1 BETWEEN 1 AND 6 JOIN tok t ON t.doc_id = a.doc_id AND t.sent_id = a.sent_id)"""),
    "said": (("pair",), f"SELECT * FROM (SELECT doc_id, sent_id, at_i, at_j, pi, {REL.format(c=f'''regexp_extract(gap, '(?:^| )({PHRASES})(?: |$)', 1)''')} AS rel_id, pj, tags FROM pair WHERE pi <> pj) WHERE rel_id IS NOT NULL"),
    "tri": (("said",), f"SELECT * FROM said WHERE regexp_matches(tags, '{SYNTAX}')"),
    "rel": (("tri", "poi"), "SELECT a.city_id, pi, pj, rel_id, count(*) AS cnt FROM tri JOIN poi a ON a.poi_id = pi JOIN poi b ON b.poi_id = pj WHERE a.city_id = b.city_id GROUP BY 1, 2, 3, 4"),
    "vec": (("rel", "poi"), f"""SELECT * FROM (SELECT r.city_id, rel_id, pi, pj, {line("a", "b")} AS dist, {TURN.format(dy="CAST(a.y - b.y AS DOUBLE)", dx="CAST(a.x - b.x AS DOUBLE)")} AS theta, CAST(cnt AS DOUBLE) AS w
      FROM rel r JOIN poi a ON a.poi_id = pi JOIN poi b ON b.poi_id = pj) WHERE dist > 0"""),
    "pv": (("vec",), "SELECT DISTINCT city_id, pi, pj, dist, theta FROM vec"),
    "one": (("vec",), """SELECT rel_id, n, d / n AS mu_d, o / n AS mu_o, greatest(dd / n - (d / n) * (d / n), 0) + 1e-6 AS s_dd, x / n - (d / n) * (o / n) AS s_do, greatest(oo / n - (o / n) * (o / n), 0) + 1e-6 AS s_oo FROM (
      SELECT rel_id, sum(w) AS n, sum(w * dist) AS d, sum(w * theta) AS o, sum(w * dist * dist) AS dd, sum(w * dist * theta) AS x, sum(w * theta * theta) AS oo FROM vec GROUP BY 1)"""),
}


def log_gauss(c: str, d: str = "dist", o: str = "theta") -> str:
    u, v = f"({d} - {c}.mu_d)", f"({o} - {c}.mu_o)"
    det = f"({c}.s_dd * {c}.s_oo - {c}.s_do * {c}.s_do)"
    return f"(-ln(2 * pi()) - 0.5 * ln({det}) - 0.5 * ({c}.s_oo * {u} * {u} - 2 * {c}.s_do * {u} * {v} + {c}.s_dd * {v} * {v}) / {det})"


BLOCKS |= {
    "lik": (("pv", "one"), f"SELECT city_id, pi, pj, one.rel_id, {log_gauss('one')} AS log_lik FROM pv, one"),
    # Two components by a fixed rule: the single one's mean moved half a deviation either way, half the weight each.
    "two": (("one",), """SELECT rel_id, m, 0.5 AS weight, mu_d + (1 - 2 * m) * 0.5 * sqrt(s_dd) AS mu_d, mu_o + (1 - 2 * m) * 0.5 * sqrt(s_oo) AS mu_o, 0.75 * s_dd AS s_dd, 0.5 * s_do AS s_do, 0.75 * s_oo AS s_oo FROM one, (VALUES (0), (1)) t(m)"""),
    "term": (("two", "vec"), f"SELECT vec.*, m, ln(weight) + {log_gauss('two')} AS t FROM vec JOIN two USING (rel_id)"),
    "logp": (("term",), "SELECT city_id, rel_id, pi, pj, dist, theta, w, max(mt) + ln(sum(exp(t - mt))) AS log_p FROM (SELECT *, max(t) OVER (PARTITION BY city_id, rel_id, pi, pj) AS mt FROM term) GROUP BY city_id, rel_id, pi, pj, dist, theta, w"),
}


def em_round(model: str, out: str) -> dict[str, tuple[tuple[str, ...], str]]:
    """Blocks of one EM round from ``model`` (rel_id, m, weight, ...) to ``out``."""
    return {
        f"{out}_t": ((model, "vec"), f"SELECT *, max(t) OVER k AS mt FROM (SELECT vec.*, m, ln(weight) + {log_gauss(model)} AS t FROM vec JOIN {model} USING (rel_id)) WINDOW k AS (PARTITION BY city_id, rel_id, pi, pj)"),
        f"{out}_r": ((f"{out}_t",), f"SELECT *, exp(t - lp) AS r FROM (SELECT *, mt + ln(sum(exp(t - mt)) OVER (PARTITION BY city_id, rel_id, pi, pj)) AS lp FROM {out}_t)"),
        f"{out}_s": ((f"{out}_r",), f"SELECT rel_id, m, sum(w * r) AS n, sum(w * r * dist) AS d, sum(w * r * theta) AS o, sum(w * r * dist * dist) AS dd, sum(w * r * dist * theta) AS x, sum(w * r * theta * theta) AS oo, sum(w * lp) AS ll, sum(w) AS a FROM {out}_r GROUP BY 1, 2"),
        out: ((f"{out}_s",), f"SELECT rel_id, m, n / a AS weight, d / n AS mu_d, o / n AS mu_o, greatest(dd / n - (d / n) * (d / n), 0) + 1e-6 AS s_dd, x / n - (d / n) * (o / n) AS s_do, greatest(oo / n - (o / n) * (o / n), 0) + 1e-6 AS s_oo, ll AS loglik FROM {out}_s"),
    }


BLOCKS |= em_round("two", "em1") | em_round("em1", "em2")
# One step of growth from the single Gaussian, for words with five statements or more.
BLOCKS |= {
    "axis": (("one",), """SELECT *, sqrt(greatest(top, 0)) AS sd, vx / sqrt(vx * vx + vy * vy) AS ex, vy / sqrt(vx * vx + vy * vy) AS ey FROM (SELECT *, CASE WHEN abs(s_do) > 1e-12 THEN s_do WHEN s_dd >= s_oo THEN 1 ELSE 0 END AS vx, CASE WHEN abs(s_do) > 1e-12 THEN top - s_dd WHEN s_dd >= s_oo THEN 0 ELSE 1 END AS vy
      FROM (SELECT *, (s_dd + s_oo) / 2 + sqrt(pow((s_dd - s_oo) / 2, 2) + s_do * s_do) AS top FROM one WHERE n >= 5))"""),
    "trial": (("axis",), """SELECT rel_id, k, m, 0.5 AS weight, mu_d + m * side * sd * ex AS mu_d, mu_o + m * side * sd * ey AS mu_o, (1 - 0.5 * m) * s_dd AS s_dd, (1 - 0.5 * m) * s_do AS s_do, (1 - 0.5 * m) * s_oo AS s_oo FROM axis, (VALUES (0, 1), (1, -1)) a(k, side), (VALUES (0), (1)) b(m)"""),
    "judged": (("trial", "vec"), f"""SELECT rel_id, k, sum(w * lp) AS ll FROM (SELECT rel_id, k, city_id, pi, pj, any_value(w) AS w, max(mt) + ln(sum(exp(t - mt))) AS lp FROM (SELECT *, max(t) OVER (PARTITION BY rel_id, k, city_id, pi, pj) AS mt FROM (
      SELECT vec.*, k, ln(weight) + {log_gauss('trial')} AS t FROM vec JOIN trial USING (rel_id))) GROUP BY 1, 2, 3, 4, 5) GROUP BY 1, 2"""),
    "ins": (("trial", "judged"), "SELECT trial.* EXCLUDE (k) FROM trial JOIN (SELECT rel_id, min({'l': -ll, 'k': k}).k AS k FROM judged GROUP BY 1) b ON b.rel_id = trial.rel_id AND b.k = trial.k"),
}
BLOCKS |= em_round("ins", "ins1") | em_round("ins1", "ins2")
BLOCKS["one_ll"] = (("one", "vec"), f"SELECT rel_id, sum(w) AS n, sum(w * lp) AS ll FROM (SELECT vec.*, {log_gauss('one')} AS lp FROM vec JOIN one USING (rel_id) WHERE n >= 5) GROUP BY 1")


def posterior(prior: str) -> dict[str, tuple[tuple[str, ...], str]]:
    p = {
        "pair_frequency": "SELECT city_id, pi, pj, rel_id, cnt / sum(cnt) OVER (PARTITION BY city_id, pi, pj) AS prior FROM rel",
        "pair_uniform": "SELECT city_id, pi, pj, rel_id, 1.0 / count(*) OVER (PARTITION BY city_id, pi, pj) AS prior FROM rel",
        "corpus_frequency": "SELECT city_id, rel_id, sum(cnt) / sum(sum(cnt)) OVER (PARTITION BY city_id) AS prior FROM rel GROUP BY 1, 2",
        "corpus_uniform": f"SELECT c.city_id, r.rel_id, 1.0 / {N_REL} AS prior FROM (SELECT DISTINCT city_id FROM rel) c, (SELECT DISTINCT rel_id FROM rel) r",
    }[prior]
    keys = "city_id, pi, pj, rel_id" if prior.startswith("pair") else "city_id, rel_id"
    return {
        f"pr_{prior}": (("rel",), p),
        f"post_{prior}": ((f"pr_{prior}", "lik", "rel"), f"""SELECT city_id, pi, pj, rel_id, coalesce(CASE WHEN sum(q) OVER k > 0 THEN q / sum(q) OVER k END, 0) AS posterior, observed FROM (
          SELECT *, CASE WHEN prior > 0 THEN exp(log_lik - max(CASE WHEN prior > 0 THEN log_lik END) OVER (PARTITION BY city_id, pi, pj)) * prior ELSE 0 END AS q FROM (
            SELECT l.city_id, l.pi, l.pj, l.rel_id, log_lik, coalesce(prior, 0) AS prior, cnt IS NOT NULL AS observed FROM lik l LEFT JOIN pr_{prior} USING ({keys}) LEFT JOIN rel USING (city_id, pi, pj, rel_id))) WINDOW k AS (PARTITION BY city_id, pi, pj)"""),
    }


for _p in ("pair_frequency", "pair_uniform", "corpus_frequency", "corpus_uniform"):
    BLOCKS |= posterior(_p)


def score_sql(post: str, scope: str = "per_relation", combine: str = "sum") -> str:
    top = {
        "per_relation": f"SELECT city_id, rel_id, max(posterior) AS top FROM {post} WHERE observed GROUP BY 1, 2",
        "all_pairs": f"SELECT city_id, rel_id, max(posterior) AS top FROM {post} GROUP BY 1, 2",
        "global": f"SELECT city_id, rel_id, max(max(posterior)) OVER (PARTITION BY city_id) AS top FROM {post} WHERE observed GROUP BY 1, 2",
        "none": f"SELECT DISTINCT city_id, rel_id, 1.0 AS top FROM {post} WHERE observed",
    }[scope]
    how = {"sum": f"sum(sh) / {N_REL}", "max": "max(sh)", "mean": "avg(sh)", "noisy_or": "1 - product(1 - sh)"}[combine]
    return f"SELECT city_id, pi, pj, {how} AS W, count(*) AS n_words FROM (SELECT p.city_id, pi, pj, CASE WHEN top > 0 THEN posterior / top ELSE 0 END AS sh FROM {post} p JOIN ({top}) n ON n.city_id = p.city_id AND n.rel_id = p.rel_id WHERE observed) GROUP BY 1, 2, 3"


def tree(source: str, weight: str, name: str, edges: str = "e", zero: str = "CAST(0 AS BIGINT)") -> dict[str, tuple[tuple[str, ...], str]]:
    """Shortest-path labels from (city_id, s) of block ``source``: least (cost, hops, predecessor)."""
    return {
        f"{name}_arc": ((edges,), f"SELECT city_id, u AS a, v AS b, {weight} AS w, edge_id FROM {edges} UNION ALL SELECT city_id, v, u, {weight}, edge_id FROM {edges}"),
        name: ((source, f"{name}_arc"), f"""SELECT city_id, s, s, {zero}, 0, CAST(-1 AS BIGINT) FROM {source}
         UNION (SELECT city_id, s, v, l.cost, l.hops, l.pred FROM (
           SELECT t.city_id, t.s, r.b AS v, min({{'cost': t.cost + r.w, 'hops': t.hops + 1, 'pred': t.v}}) AS l FROM {name} t JOIN {name}_arc r ON r.city_id = t.city_id AND r.a = t.v GROUP BY 1, 2, 3) n
           WHERE NOT EXISTS (SELECT 1 FROM recurring.{name} o WHERE o.city_id = n.city_id AND o.s = n.s AND o.v = n.v AND {{'cost': o.cost, 'hops': o.hops, 'pred': o.pred}} <= n.l))"""),
    }


def walk(pairs: str, name: str, out: str) -> dict[str, tuple[tuple[str, ...], str]]:
    """Path rows (city_id, pair_id, seq, vertex_id) by following predecessors of tree ``name`` back from t."""
    return {
        out: ((pairs, name), f"""SELECT p.city_id, p.pair_id, p.s, t.hops AS seq, t.v AS vertex_id, t.pred FROM {pairs} p JOIN {name} t ON t.city_id = p.city_id AND t.s = p.s AND t.v = p.t
          UNION ALL SELECT w.city_id, w.pair_id, w.s, t.hops, t.v, t.pred FROM {out} w JOIN {name} t ON t.city_id = w.city_id AND t.s = w.s AND t.v = w.pred"""),
        f"{out}_e": ((out, "e"), f"SELECT w.city_id, w.pair_id, w.seq, w.vertex_id, e.edge_id, e.len_dm FROM {out} w LEFT JOIN e ON e.city_id = w.city_id AND e.u = least(w.vertex_id, w.pred) AND e.v = greatest(w.vertex_id, w.pred)"),
    }


N_TRIPS = "(SELECT CASE WHEN min(n) >= 100 THEN 100 ELSE 10 END FROM (SELECT count(*) AS n FROM v GROUP BY city_id))"
BLOCKS |= {
    "ext": (("v",), "SELECT city_id, sqrt(CAST((max(x) - min(x)) * (max(x) - min(x)) + (max(y) - min(y)) * (max(y) - min(y)) AS DOUBLE)) AS extent FROM v GROUP BY 1"),
    "cand": (("v",), "SELECT a.city_id, a.vertex_id AS s, b.vertex_id AS t, a.x AS sx, a.y AS sy, b.x AS tx, b.y AS ty FROM (SELECT *, row_number() OVER (PARTITION BY city_id ORDER BY md5('42s:' || vertex_id), vertex_id) AS r FROM v) a JOIN (SELECT *, row_number() OVER (PARTITION BY city_id ORDER BY md5('42t:' || vertex_id), vertex_id) AS r FROM v) b ON a.city_id = b.city_id WHERE a.r <= 60 AND b.r <= 60 AND a.vertex_id <> b.vertex_id"),
    "trip": (("cand", "ext"), f"""SELECT *, city_id || '/i/30-50/' || trip_id AS pair_id FROM (SELECT cand.*, row_number() OVER (PARTITION BY cand.city_id ORDER BY md5('42:' || s || ':' || t), s, t) AS trip_id FROM cand JOIN ext ON ext.city_id = cand.city_id
      WHERE {LINE.format(x1="sx", x2="tx", y1="sy", y2="ty")} / extent >= 0.3 AND {LINE.format(x1="sx", x2="tx", y1="sy", y2="ty")} / extent < 0.5) WHERE trip_id <= {N_TRIPS}"""),
    "tsrc": (("trip",), "SELECT DISTINCT city_id, s FROM trip"),
    "snap": (("poi", "v"), f"SELECT p.city_id, p.poi_id, min({{'d': {line('p', 'v')}, 'v': v.vertex_id}}) AS b FROM poi p JOIN v ON v.city_id = p.city_id GROUP BY 1, 2"),
    "clo": (("post_pair_frequency",), score_sql("post_pair_frequency")),
    "cp": (("clo", "snap"), "SELECT c.city_id, pi || '>' || pj AS pair_id, pi, pj, W, least(a.b.v, b.b.v) AS s, greatest(a.b.v, b.b.v) AS t FROM clo c JOIN snap a ON a.poi_id = pi JOIN snap b ON b.poi_id = pj"),
    "csrc": (("cp",), "SELECT DISTINCT city_id, s FROM cp"),
}
BLOCKS |= tree("tsrc", "len_dm", "ttree") | walk("trip", "ttree", "tpath") | tree("csrc", "len_dm", "ctree") | walk("cp", "ctree", "cpath")
BLOCKS |= {
    "fac": (("cpath_e", "cp"), "SELECT q.city_id, edge_id, count(*) AS n_paths, product(1 - 0.2 * W) AS f02, product(1 - 0.5 * W) AS f05, product(1 - W) AS f10 FROM (SELECT DISTINCT city_id, pair_id, edge_id FROM cpath_e WHERE edge_id IS NOT NULL) q JOIN cp ON cp.city_id = q.city_id AND cp.pair_id = q.pair_id GROUP BY 1, 2"),
    "cost": (("fac", "e"), "SELECT e.city_id, e.edge_id, u, v, len_dm, coalesce(n_paths, 0) AS n_paths, len_dm * coalesce(f02, 1) AS cost_020, len_dm * coalesce(f05, 1) AS cost_050, len_dm * coalesce(f10, 1) AS cost_100 FROM e LEFT JOIN fac ON fac.city_id = e.city_id AND fac.edge_id = e.edge_id"),
}
BLOCKS |= tree("tsrc", "cost_100", "rtree", "cost", "CAST(0 AS DOUBLE)")


def in_shape(shape: str) -> str:
    d = LINE.format(x1="sx", x2="tx", y1="sy", y2="ty")
    along = f"(((p.x - (sx + tx) / 2) * (tx - sx) + (p.y - (sy + ty) / 2) * (ty - sy)) / {d})"
    off = f"(((p.y - (sy + ty) / 2) * (tx - sx) - (p.x - (sx + tx) / 2) * (ty - sy)) / {d})"
    return {
        "drawn": f"pow({along} / (0.8 * {d}), 2) + pow({off} / (0.55 * {d}), 2) <= 1",
        "box": f"abs({along}) <= {d} / 2 AND abs({off}) <= {d} / 2",
        "confocal": f"{LINE.format(x1='p.x', x2='sx', y1='p.y', y2='sy')} + {LINE.format(x1='p.x', x2='tx', y1='p.y', y2='ty')} <= 1.6 * {d}",
    }[shape]


for _s in ("drawn", "box", "confocal"):
    BLOCKS[f"node_{_s}"] = (("trip", "poi"), f"SELECT t.city_id, t.pair_id, p.poi_id, {LINE.format(x1='p.x', x2='sx', y1='p.y', y2='sy')} AS ds, {LINE.format(x1='p.x', x2='tx', y1='p.y', y2='ty')} AS dt FROM trip t JOIN poi p ON p.city_id = t.city_id WHERE {in_shape(_s)}")
BLOCKS |= {
    "ends": (("node_drawn",), "SELECT city_id, pair_id, min({'d': ds, 'p': poi_id}).p AS entry, min({'d': dt, 'p': poi_id}).p AS exit FROM node_drawn GROUP BY 1, 2"),
    "hop_e": (("clo", "pv", "node_drawn"), """SELECT n.city_id, n.pair_id, b.pi AS a, b.pj AS b, b.dist AS w FROM node_drawn n JOIN (SELECT city_id, pi, pj, min(dist) AS dist FROM (SELECT city_id, pi, pj, dist FROM pv UNION ALL SELECT city_id, pj, pi, dist FROM pv) GROUP BY 1, 2, 3) b ON b.city_id = n.city_id AND b.pi = n.poi_id
      JOIN node_drawn m ON m.city_id = n.city_id AND m.pair_id = n.pair_id AND m.poi_id = b.pj"""),
    "hop": (("ends", "hop_e"), """SELECT city_id, pair_id, entry, CAST(0 AS DOUBLE), 0, CAST(-1 AS BIGINT) FROM ends
      UNION (SELECT city_id, pair_id, v, l.cost, l.hops, l.pred FROM (SELECT t.city_id, t.pair_id, r.b AS v, min({'cost': t.cost + r.w, 'hops': t.hops + 1, 'pred': t.v}) AS l FROM hop t JOIN hop_e r ON r.city_id = t.city_id AND r.pair_id = t.pair_id AND r.a = t.v GROUP BY 1, 2, 3) n
      WHERE NOT EXISTS (SELECT 1 FROM recurring.hop o WHERE o.city_id = n.city_id AND o.pair_id = n.pair_id AND o.v = n.v AND {'cost': o.cost, 'hops': o.hops, 'pred': o.pred} <= n.l))"""),
}
#: Blocks that are recursive tables, with their columns and key.
RECURSIVE = {t: f"{t}(city_id, s, v, cost, hops, pred) USING KEY (city_id, s, v)" for t in ("ttree", "ctree", "rtree")} | {"hop": "hop(city_id, pair_id, v, cost, hops, pred) USING KEY (city_id, pair_id, v)"}


# ---------------------------------------------------------------- the experiments, with one Gaussian per word and costs on a binary grid

#: Parts of a decimetre that a pinned cost is a multiple of.
GRID = 1024
ALPHAS = (0.2, 0.4, 0.5, 0.6, 0.8, 1.0)
CHANGES = ("len_change", "er_gain", "er_drop", "pop_change")


def tag(alpha: float) -> str:
    return f"{round(100 * alpha):03d}"


def labels(name: str, source: str, arcs: str, weight: str) -> dict[str, tuple[tuple[str, ...], str]]:
    """Like ``tree``, over arcs that exist already."""
    RECURSIVE[name] = f"{name}(city_id, s, v, cost, hops, pred) USING KEY (city_id, s, v)"
    return {
        name: ((source, arcs), f"""SELECT city_id, s, s, CAST(0 AS DOUBLE), 0, CAST(-1 AS BIGINT) FROM {source}
         UNION (SELECT city_id, s, v, l.cost, l.hops, l.pred FROM (
           SELECT t.city_id, t.s, r.b AS v, min({{'cost': t.cost + r.{weight}, 'hops': t.hops + 1, 'pred': t.v}}) AS l FROM {name} t JOIN {arcs} r ON r.city_id = t.city_id AND r.a = t.v GROUP BY 1, 2, 3) n
           WHERE NOT EXISTS (SELECT 1 FROM recurring.{name} o WHERE o.city_id = n.city_id AND o.s = n.s AND o.v = n.v AND {{'cost': o.cost, 'hops': o.hops, 'pred': o.pred}} <= n.l))"""),
    }


FACTORS = ", ".join(f"product(1 - CAST({a} AS DOUBLE) * W) AS f{tag(a)}" for a in ALPHAS)
COSTS = ", ".join(f"round(len_dm * coalesce(f{tag(a)}, 1) * {GRID}) / {GRID} AS c{tag(a)}" for a in ALPHAS)
NAMES = ", ".join(f"c{tag(a)}" for a in ALPHAS)
BLOCKS |= {
    "pfac": (("cpath_e", "cp"), f"SELECT q.city_id, edge_id, {FACTORS} FROM (SELECT DISTINCT city_id, pair_id, edge_id FROM cpath_e WHERE edge_id IS NOT NULL) q JOIN cp ON cp.city_id = q.city_id AND cp.pair_id = q.pair_id GROUP BY 1, 2"),
    "pcost": (("pfac", "e"), f"SELECT e.city_id, e.edge_id, u, v, CAST(len_dm AS DOUBLE) AS len, len_dm, {COSTS} FROM e LEFT JOIN pfac ON pfac.city_id = e.city_id AND pfac.edge_id = e.edge_id"),
    "parc": (("pcost",), f"SELECT city_id, u AS a, v AS b, len, {NAMES} FROM pcost UNION ALL SELECT city_id, v, u, len, {NAMES} FROM pcost"),
    "xtrip": (("trip",), "SELECT city_id, pair_id, '30-50' AS bracket, s, t, sx, sy, tx, ty FROM trip"),
    "csrc2": (("cand",), "SELECT DISTINCT city_id, s FROM cand"),
}
BLOCKS |= labels("xreach", "csrc2", "parc", "len")
BRACKET = "(VALUES " + ", ".join(f"('{lo}-{lo + 10}', CAST({lo / 100} AS DOUBLE), CAST({(lo + 10) / 100} AS DOUBLE))" for lo in range(10, 60, 10)) + ") b(bracket, lo, hi)"
BLOCKS["ytrip"] = (("cand", "ext", "xreach"), f"""SELECT *, city_id || '/ii/' || bracket || '/' || trip_id AS pair_id FROM (
  SELECT c.*, bracket, row_number() OVER (PARTITION BY c.city_id, bracket ORDER BY md5('42:' || c.s || ':' || c.t), c.s, c.t) AS trip_id FROM cand c JOIN ext ON ext.city_id = c.city_id
  JOIN xreach r ON r.city_id = c.city_id AND r.s = c.s AND r.v = c.t, {BRACKET} WHERE r.cost / 10 / extent >= lo AND r.cost / 10 / extent < hi) WHERE trip_id <= {N_TRIPS}""")
BLOCKS["pclo"] = (("clo", "pv"), """SELECT b.city_id, b.pi, b.pj, min(dist) AS dist, max(W) AS W FROM (SELECT pv.city_id, pv.pi, pv.pj, dist, W FROM pv JOIN clo USING (city_id, pi, pj) UNION ALL SELECT pv.city_id, pv.pj, pv.pi, dist, W FROM pv JOIN clo USING (city_id, pi, pj)) b GROUP BY 1, 2, 3""")


def hops(x: str, weight: str, suffix: str = "") -> dict[str, tuple[tuple[str, ...], str]]:
    """The sequences of places of the trips of block ``{x}trip``, under a weight of dist and W."""
    n = f"{x}hop{suffix}"
    RECURSIVE[n] = f"{n}(city_id, pair_id, v, cost, hops, pred) USING KEY (city_id, pair_id, v)"
    return {
        f"{n}_e": (("pclo", f"{x}node"), f"SELECT n.city_id, n.pair_id, b.pi AS a, b.pj AS b, {weight} AS w FROM {x}node n JOIN pclo b ON b.city_id = n.city_id AND b.pi = n.poi_id JOIN {x}node m ON m.city_id = n.city_id AND m.pair_id = n.pair_id AND m.poi_id = b.pj"),
        n: ((f"{x}ends", f"{n}_e"), f"""SELECT city_id, pair_id, entry, CAST(0 AS DOUBLE), 0, CAST(-1 AS BIGINT) FROM {x}ends
          UNION (SELECT city_id, pair_id, v, l.cost, l.hops, l.pred FROM (SELECT t.city_id, t.pair_id, r.b AS v, min({{'cost': t.cost + r.w, 'hops': t.hops + 1, 'pred': t.v}}) AS l FROM {n} t JOIN {n}_e r ON r.city_id = t.city_id AND r.pair_id = t.pair_id AND r.a = t.v GROUP BY 1, 2, 3) n
          WHERE NOT EXISTS (SELECT 1 FROM recurring.{n} o WHERE o.city_id = n.city_id AND o.pair_id = n.pair_id AND o.v = n.v AND {{'cost': o.cost, 'hops': o.hops, 'pred': o.pred}} <= n.l))"""),
    }


def journey(x: str, alphas: tuple[float, ...]) -> dict[str, tuple[tuple[str, ...], str]]:
    """The three planners on the trips of block ``{x}trip``: path rows {x}rows, per-path measures {x}m, changes {x}rel."""
    t = f"{x}trip"
    out = {
        f"{x}node": ((t, "poi"), f"SELECT t.city_id, t.pair_id, p.poi_id, {LINE.format(x1='p.x', x2='sx', y1='p.y', y2='sy')} AS ds, {LINE.format(x1='p.x', x2='tx', y1='p.y', y2='ty')} AS dt FROM {t} t JOIN poi p ON p.city_id = t.city_id WHERE {in_shape('drawn')}"),
        f"{x}ends": ((f"{x}node",), f"SELECT city_id, pair_id, min({{'d': ds, 'p': poi_id}}).p AS entry, min({{'d': dt, 'p': poi_id}}).p AS exit FROM {x}node GROUP BY 1, 2"),
        **hops(x, "b.dist"),
        f"{x}seq": ((f"{x}hop", f"{x}ends"), f"SELECT h.city_id, h.pair_id, h.hops AS seq, h.v AS poi_id, h.pred FROM {x}ends e JOIN {x}hop h ON h.city_id = e.city_id AND h.pair_id = e.pair_id AND h.v = e.exit UNION ALL SELECT h.city_id, h.pair_id, h.hops, h.v, h.pred FROM {x}seq q JOIN {x}hop h ON h.city_id = q.city_id AND h.pair_id = q.pair_id AND h.v = q.pred"),
        f"{x}stop": ((f"{x}seq", "snap", t), f"""SELECT city_id, pair_id, stop, vertex_id FROM (SELECT *, lag(vertex_id) OVER (PARTITION BY pair_id ORDER BY stop) AS p FROM (
          SELECT q.city_id, pair_id, seq + 1 AS stop, snap.b.v AS vertex_id FROM {x}seq q JOIN snap ON snap.city_id = q.city_id AND snap.poi_id = q.poi_id
          UNION ALL SELECT city_id, pair_id, 0, s FROM {t} WHERE pair_id IN (SELECT pair_id FROM {x}seq) UNION ALL SELECT city_id, pair_id, 1000000, t FROM {t} WHERE pair_id IN (SELECT pair_id FROM {x}seq))) WHERE p IS NULL OR p <> vertex_id"""),
        f"{x}leg": ((f"{x}stop",), f"SELECT *, s || '>' || t AS leg_id FROM (SELECT city_id, pair_id, row_number() OVER k AS leg, vertex_id AS s, lead(vertex_id) OVER k AS t FROM {x}stop WINDOW k AS (PARTITION BY pair_id ORDER BY stop)) WHERE t IS NOT NULL"),
        f"{x}src": ((t, f"{x}leg"), f"SELECT city_id, s FROM {t} UNION SELECT city_id, s FROM {x}leg"),
        f"{x}way": ((t, f"{x}leg"), f"SELECT city_id, 'trip' AS kind, pair_id, s, t FROM {t} UNION ALL SELECT DISTINCT city_id, 'leg', leg_id, s, t FROM {x}leg"),
    }

    def walked(name: str, tree: str, which: str) -> dict[str, tuple[tuple[str, ...], str]]:
        return {
            f"{name}_w": ((f"{x}way", tree), f"SELECT p.city_id, p.kind, p.pair_id, p.s, t.hops AS seq, t.v AS vertex_id, t.pred FROM {x}way p JOIN {tree} t ON t.city_id = p.city_id AND t.s = p.s AND t.v = p.t {which} UNION ALL SELECT w.city_id, w.kind, w.pair_id, w.s, t.hops, t.v, t.pred FROM {name}_w w JOIN {tree} t ON t.city_id = w.city_id AND t.s = w.s AND t.v = w.pred"),
            name: ((f"{name}_w", "pcost"), f"SELECT w.city_id, w.kind, w.pair_id, w.seq, w.vertex_id, e.edge_id FROM {name}_w w LEFT JOIN pcost e ON e.city_id = w.city_id AND e.u = least(w.vertex_id, w.pred) AND e.v = greatest(w.vertex_id, w.pred)"),
        }

    out |= labels(f"{x}lt", f"{x}src", "parc", "len") | walked(f"{x}lp", f"{x}lt", "WHERE p.kind = 'trip'")
    rows, need = [], [f"{x}lp", t, f"{x}leg"]
    for a in alphas:
        k = tag(a)
        out |= labels(f"{x}t{k}", f"{x}src", "parc", f"c{k}") | walked(f"{x}p{k}", f"{x}t{k}", "")
        out[f"{x}done{k}"] = ((f"{x}leg", f"{x}p{k}"), f"SELECT pair_id FROM {x}leg l LEFT JOIN (SELECT city_id, pair_id AS leg_id, max(seq) AS n FROM {x}p{k} WHERE kind = 'leg' GROUP BY 1, 2) q USING (city_id, leg_id) GROUP BY 1 HAVING count(*) = count(n)")
        out[f"{x}h{k}"] = ((f"{x}leg", f"{x}p{k}", f"{x}done{k}"), f"""SELECT city_id, pair_id, row_number() OVER (PARTITION BY pair_id ORDER BY leg, seq) - 1 AS seq, vertex_id, edge_id FROM (
          SELECT l.city_id, l.pair_id, leg, p.seq, p.vertex_id, p.edge_id FROM {x}leg l JOIN {x}p{k} p ON p.kind = 'leg' AND p.city_id = l.city_id AND p.pair_id = l.leg_id WHERE l.pair_id IN (SELECT pair_id FROM {x}done{k}) AND (p.seq > 0 OR leg = 1))""")
        al = f"CAST({a} AS DOUBLE) AS alpha"
        rows.append(f"""SELECT {al}, 'plain' AS algo, false AS fallback, city_id, pair_id, seq, vertex_id, edge_id FROM {x}lp UNION ALL SELECT {al}, 'enriched', false, city_id, pair_id, seq, vertex_id, edge_id FROM {x}p{k} WHERE kind = 'trip'
          UNION ALL SELECT {al}, 'poi_hop', false, city_id, pair_id, seq, vertex_id, edge_id FROM {x}h{k} UNION ALL SELECT {al}, 'poi_hop', true, city_id, pair_id, seq, vertex_id, edge_id FROM {x}p{k} WHERE kind = 'trip' AND pair_id NOT IN (SELECT pair_id FROM {x}done{k})""")
        need += [f"{x}p{k}", f"{x}h{k}", f"{x}done{k}"]
    own = "CASE " + " ".join(f"WHEN alpha = CAST({a} AS DOUBLE) THEN c{tag(a)}" for a in alphas) + " END"
    out[f"{x}rows"] = (tuple(need), " UNION ALL ".join(rows))
    out[f"{x}m"] = ((f"{x}rows", "pcost", "vpop"), f"""SELECT *, CASE WHEN d > 0 THEN c / d END AS er FROM (SELECT alpha, algo, r.city_id, pair_id, coalesce(sum(len_dm), 0) AS d, coalesce(sum({own}), 0) AS c, count(r.edge_id) AS hops, coalesce(sum(photos), 0) AS popularity
      FROM {x}rows r LEFT JOIN pcost e ON e.city_id = r.city_id AND e.edge_id = r.edge_id LEFT JOIN vpop q ON q.city_id = r.city_id AND q.vertex_id = r.vertex_id GROUP BY 1, 2, 3, 4)""")
    over = lambda n, z: f"CASE WHEN {z} <> 0 THEN CAST({n} AS DOUBLE) / {z} END"
    out[f"{x}rel"] = ((f"{x}m",), f"""SELECT m.alpha, m.algo, m.city_id, m.pair_id, split_part(m.pair_id, '/', 3) AS bracket, CAST(m.d AS BIGINT) AS d, CAST(b.d AS BIGINT) AS d0, m.er, b.er AS er0, CAST(m.popularity AS BIGINT) AS popularity, CAST(b.popularity AS BIGINT) AS p0,
      {over('m.d', 'b.d')} - 1 AS len_change, {over('b.er', 'm.er')} - 1 AS er_gain, 1 - {over('m.er', 'b.er')} AS er_drop, {over('m.popularity', 'b.popularity')} - 1 AS pop_change
      FROM {x}m m JOIN {x}m b ON b.alpha = m.alpha AND b.pair_id = m.pair_id AND b.algo = 'plain' WHERE m.algo <> 'plain'""")
    return out


BLOCKS |= {
    "tsrc2": (("trip",), "SELECT DISTINCT city_id, t AS s FROM trip"),
    "nends": (("node_drawn", "snap", "trip", "ttree", "utree"), """SELECT n.city_id, n.pair_id, min({'d': a.cost, 'p': n.poi_id}).p AS entry, min({'d': b.cost, 'p': n.poi_id}).p AS exit FROM node_drawn n JOIN snap ON snap.city_id = n.city_id AND snap.poi_id = n.poi_id
      JOIN trip t ON t.city_id = n.city_id AND t.pair_id = n.pair_id JOIN ttree a ON a.city_id = n.city_id AND a.s = t.s AND a.v = snap.b.v JOIN utree b ON b.city_id = n.city_id AND b.s = t.t AND b.v = snap.b.v GROUP BY 1, 2"""),
    "around": (("tsrc", "e"), """SELECT city_id, s, s, 0 FROM tsrc UNION (SELECT r.city_id, r.s, a.v, min(r.hops + 1) FROM around r JOIN (SELECT city_id, u, v FROM e UNION ALL SELECT city_id, v, u FROM e) a ON a.city_id = r.city_id AND a.u = r.v
      WHERE r.hops < 6 AND NOT EXISTS (SELECT 1 FROM recurring.around o WHERE o.city_id = r.city_id AND o.s = r.s AND o.v = a.v) GROUP BY 1, 2, 3)"""),
}
RECURSIVE["around"] = "around(city_id, s, v, hops) USING KEY (city_id, s, v)"
BLOCKS |= tree("tsrc2", "len_dm", "utree")
RECURSIVE["utree"] = "utree(city_id, s, v, cost, hops, pred) USING KEY (city_id, s, v)"
BLOCKS |= journey("x", (0.2, 0.4, 0.5, 0.6, 0.8, 1.0)) | journey("y", (0.5, 1.0)) | hops("x", "b.dist * (1 - b.W)", "d") | hops("x", "1 - b.W", "w")
RECURSIVE |= {f"{x}{k}": f"{x}{k}" for x in "xy" for k in ("seq",)}


def means(mode: str = "mean_of_ratios") -> str:
    if mode == "mean_of_ratios":
        return ", ".join(f"round(avg({c}), 4) AS {c}" for c in CHANGES)
    ratio = lambda n, z: f"CASE WHEN avg({z}) <> 0 THEN avg({n}) / avg({z}) END"
    return f"round({ratio('d', 'd0')} - 1, 4) AS len_change, round({ratio('er0', 'er')} - 1, 4) AS er_gain, round(1 - {ratio('er', 'er0')}, 4) AS er_drop, round({ratio('popularity', 'p0')} - 1, 4) AS pop_change"


def summary(block: str, keys: str, where: str = "true", mode: str = "mean_of_ratios") -> str:
    return f"SELECT {keys}, count(*) AS trips, count(*) FILTER (p0 = 0) AS n_undefined, {means(mode)} FROM {block} WHERE {where} GROUP BY ALL"


def sql(final: str, *need: str) -> str:
    """``final`` with the blocks it needs before it."""
    order: list[str] = []

    def visit(name: str) -> None:
        if name not in order:
            for x in BLOCKS[name][0]:
                visit(x)
            order.append(name)

    for n in need:
        visit(n)
    parts = [f"{RECURSIVE.get(n, n)} AS ({BLOCKS[n][1]})" for n in order]
    return f"WITH RECURSIVE {', '.join(parts)} {final}" if parts else final
