"""DuckDB SQL for the mining queries, made independently of the engine: recursive unions, lists of
seeds, and explicit paths and captured patterns, one block of CTEs an iteration."""

from __future__ import annotations

from kgfeat.params import SUBCLASS, TYPE, MiningParams
from kgfeat.sources import kgview

CANON = {
    "same_part": "SELECT 'part:'||p_partkey AS v, min('part:'||p_partkey) OVER (PARTITION BY p_name, p_brand, p_type) AS c FROM part",
    "same_doc": "SELECT 'doc:'||doc_id AS v, min('doc:'||doc_id) OVER (PARTITION BY md5(text)) AS c FROM documents WHERE text IS NOT NULL",
    "same_user": "SELECT DISTINCT 'user:'||user_id AS v, 'customer:'||user_id AS c FROM events JOIN customer ON user_id = c_custkey",
}


def _listed(col: str, entries: tuple[str, ...]) -> str:
    if not entries:
        return "false"
    return "(" + " OR ".join(f"starts_with({col}, '{e[:-1]}')" if e.endswith("*") else f"{col} = '{e}'" for e in entries) + ")"


def base(view: str | tuple[str, ...], seed: str, p: MiningParams, full: bool = False, merged: dict[str, str] | None = None, more: str = "") -> list[str]:
    """merged: predicates to rename; more: SQL of further triples. CTEs t, seeds, inst, sub, arcs, arc_ok, reach(seed, v, dist), lev(v, cls, level), tsup, tf."""
    parts = kgview.VIEWS[view] if isinstance(view, str) else view
    same = [x for x in parts if x in CANON] if p.canonicalise else []
    canon = " UNION ALL ".join(CANON[x] for x in same) or "SELECT NULL::VARCHAR AS v, NULL::VARCHAR AS c WHERE false"
    keep = f"WHERE p <> '{p.identity}'" if p.canonicalise else ""
    deg = "SELECT src AS v, count(*) AS n FROM arcs GROUP BY 1"
    both = "SELECT src, pred, dst FROM arcs"
    if p.u:
        deg = "SELECT v, count(*) AS n FROM (SELECT src AS v FROM arcs UNION ALL SELECT dst FROM arcs WHERE src <> dst) GROUP BY 1"
        both += " UNION SELECT dst, pred, src FROM arcs"
    hub = "SELECT NULL::VARCHAR AS v WHERE false" if p.d is None else f"SELECT v FROM deg WHERE n > {p.d}"
    named = "CASE p " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in (merged or {'': ''}).items()) + " ELSE p END"
    bound = "" if full else f"WHERE r.dist < {p.k}"
    walk = "SELECT seed, seed AS v, 0 AS dist FROM seeds UNION SELECT r.seed, a.dst, r.dist + 1 FROM walk r JOIN arc_ok a ON a.src = r.v " + bound
    if full:  # distances up to a bound that no shortest way can exceed in these views
        walk += "WHERE r.dist < 12"
    t_bound = "" if p.t is None else f" AND level < {p.t}"
    first = "SELECT v, cls, 1 AS level FROM inst" + (" WHERE false" if p.t == 0 else "")
    return [
        f"raw AS MATERIALIZED (SELECT DISTINCT s, {named} AS p, o FROM ({kgview.duck_triples(view)}{more}))",
        f"canon AS MATERIALIZED ({canon})",
        f"t AS MATERIALIZED (SELECT DISTINCT coalesce(a.c, s) AS s, p, coalesce(b.c, o) AS o FROM raw LEFT JOIN canon a ON a.v = s LEFT JOIN canon b ON b.v = o {keep})",
        f"seeds AS MATERIALIZED (SELECT DISTINCT coalesce(c, seed) AS seed FROM ({kgview.duck_seeds(seed)}) x LEFT JOIN canon ON v = seed)",
        f"inst AS MATERIALIZED (SELECT DISTINCT s AS v, o AS cls FROM t WHERE p = '{TYPE}')",
        f"sub AS MATERIALIZED (SELECT DISTINCT s AS cls, o AS sup FROM t WHERE p = '{SUBCLASS}')",
        f"arcs AS MATERIALIZED (SELECT s AS src, p AS pred, o AS dst FROM t WHERE NOT {_listed('p', p.b_predicates)})",
        f"deg AS MATERIALIZED ({deg})",
        f"hub AS MATERIALIZED ({hub})",
        f"bad_cls AS (SELECT cls FROM (SELECT cls FROM inst UNION SELECT cls FROM sub UNION SELECT sup FROM sub) WHERE {_listed('cls', p.b_exp_types)} UNION SELECT sub.cls FROM sub JOIN bad_cls b ON sub.sup = b.cls)",
        "banned AS MATERIALIZED (SELECT DISTINCT v FROM inst JOIN bad_cls USING (cls))",
        f"arc_ok AS MATERIALIZED (SELECT src, pred, dst FROM ({both}) WHERE src NOT IN (SELECT v FROM hub) AND dst NOT IN (SELECT v FROM banned))",
        f"walk AS ({walk})",
        "reach AS MATERIALIZED (SELECT seed, v, min(dist) AS dist FROM walk WHERE v <> seed GROUP BY ALL)",
        "rv AS MATERIALIZED (SELECT DISTINCT v FROM reach)",
        f"climb AS ({first} UNION SELECT c.v, s.sup, c.level + 1 FROM climb c JOIN sub s ON s.cls = c.cls{t_bound})",
        f"lev AS MATERIALIZED (SELECT v, cls, min(level) AS level FROM climb SEMI JOIN rv USING (v) WHERE NOT {_listed('cls', p.b_gen_types)} GROUP BY ALL" + (" UNION ALL SELECT v, 'TOP', 0 FROM rv)" if p.use_top else ")"),
        "tsup AS MATERIALIZED (SELECT cls, count(DISTINCT seed) AS n FROM reach JOIN lev USING (v) GROUP BY 1)",
        f"tf AS MATERIALIZED (SELECT cls FROM tsup WHERE n >= {p.l_min if p.type_filter else 0})",
        f"near AS MATERIALIZED (SELECT v, count(*) AS n FROM reach GROUP BY 1 HAVING count(*) >= {p.l_min}" + (f" AND count(*) <= {p.l_max})" if p.l_max is not None else ")"),
    ]


def with_(ctes: list[str], body: str) -> str:
    return "WITH RECURSIVE " + ", ".join(ctes) + " " + body


def mining(p: MiningParams, general: tuple[tuple[str, str], ...] = ()) -> list[str]:
    """general: a predicate hierarchy to mine, (predicate, more general one). CTEs f0 .. fk: the selected path features (fid, len, ispat, n, sup) after each iteration; x1 .. xk."""
    patterns = "pattern" in p.kinds
    high = "" if p.l_max is None else f" AND n <= {p.l_max}"
    out = [
        "elem AS MATERIALIZED (SELECT v, v AS e, false AS isc FROM rv" + (" UNION ALL SELECT v, cls, true FROM lev SEMI JOIN tf USING (cls))" if patterns else ")"),
        "up AS (SELECT cls AS e, sup AS a FROM sub UNION SELECT v, cls FROM inst SEMI JOIN rv USING (v) UNION SELECT u.e, s.sup FROM up u JOIN sub s ON s.cls = u.a)",
        "anc AS MATERIALIZED (SELECT e, a FROM up UNION SELECT e, e FROM elem UNION SELECT e, 'TOP' FROM elem)",
        "f0 AS (SELECT ''::VARCHAR AS fid, 0 AS len, false AS ispat, 0::BIGINT AS n, ''::VARCHAR AS sup, false AS endc WHERE false)",
        "p1 AS MATERIALIZED (SELECT '-['||pred||']-> '||dst AS pid, ''::VARCHAR AS was, pred, dst AS last, list_sort(list(DISTINCT src)) AS ss FROM arc_ok JOIN seeds ON src = seed WHERE dst IN (SELECT v FROM reach WHERE dist = 1) GROUP BY pred, dst)",
        "g0 AS (SELECT ''::VARCHAR AS pid, ''::VARCHAR AS fid, []::VARCHAR[] AS ps, []::VARCHAR[] AS es, false AS ispat, []::VARCHAR[] AS pre)",
    ]
    pel, preds = "", lambda h: "a.ps = b.ps"
    if general:
        steps = ", ".join(f"('{a}', '{b}')" for a, b in general)
        out += [
            f"gen(p, g, l) AS (SELECT a, b, 1 FROM (VALUES {steps}) x(a, b) UNION SELECT gen.p, x.b, l + 1 FROM gen JOIN (VALUES {steps}) x(a, b) ON x.a = gen.g WHERE l < {p.predicate_levels})",
            "pel AS MATERIALIZED (SELECT DISTINCT pred, pred AS as_pred, false AS isup FROM arc_ok UNION SELECT p, g, true FROM gen UNION SELECT g, g, true FROM gen)",
            "panc AS MATERIALIZED (SELECT p AS e, g AS a FROM gen UNION SELECT p, p FROM gen UNION SELECT g, g FROM gen UNION SELECT pred, pred FROM arc_ok)",
        ]
        pel = " JOIN pel ON pel.pred = q.pred"
        preds = lambda h: " AND ".join(f"EXISTS (SELECT 1 FROM panc WHERE e = a.ps[{i}] AND panc.a = b.ps[{i}])" for i in range(1, h + 1))
    as_pred, up = ("as_pred", " OR isup") if general else ("q.pred", "")
    for h in range(1, p.k + 1):
        if h > 1:
            out.append(f"p{h} AS MATERIALIZED (SELECT q.pid||' -['||arc_ok.pred||']-> '||dst AS pid, q.pid AS was, arc_ok.pred, dst AS last, ss FROM next{h - 1} q JOIN arc_ok ON src = q.last WHERE EXISTS (SELECT 1 FROM reach r WHERE r.v = dst AND r.dist = {h} AND list_contains(q.ss, r.seed)))")
        sep = "" if h == 1 else "g.fid||' '||"
        out.append(f"x{h} AS MATERIALIZED (SELECT q.pid, {sep}'-['||{as_pred}||']-> '||e AS fid, list_append(g.ps, {as_pred}) AS ps, list_append(g.es, e) AS es, isc, g.ispat OR isc{up} AS ispat, CASE WHEN g.fid = '' THEN g.pre ELSE list_append(g.pre, g.fid) END AS pre, ss FROM p{h} q JOIN g{h - 1} g ON g.pid = q.was JOIN elem ON elem.v = q.last{pel})")
        out.append(f"c{h} AS MATERIALIZED (SELECT *, len(ul) AS n, md5(array_to_string(ul, ',')) AS sup FROM (SELECT fid, any_value(ps) AS ps, any_value(es) AS es, any_value(isc) AS isc, any_value(ispat) AS ispat, any_value(pre) AS pre, count(DISTINCT pid) AS np, max(len(ss)) AS largest, list_sort(list_distinct(flatten(list(ss)))) AS ul FROM x{h} GROUP BY fid))")
        prune = f"n >= {p.l_min}" if p.prune else "true"
        out.append(f"m{h} AS MATERIALIZED (SELECT * FROM c{h} WHERE ispat AND {prune}" + (" AND np > 1)" if p.drop_single else ")"))
        if p.specificity == "off":
            out.append(f"s{h} AS MATERIALIZED (SELECT * FROM m{h})")
        else:
            joins = " ".join(f"JOIN anc a{i} ON a{i}.e = a.es[{i}] AND a{i}.a = b.es[{i}]" for i in range(1, h + 1))
            out.append(f"s{h} AS MATERIALIZED (SELECT * FROM m{h} WHERE fid NOT IN (SELECT b.fid FROM m{h} b JOIN m{h} a ON a.sup = b.sup AND {preds(h)} AND a.fid <> b.fid {joins}))")
        c3 = "AND (NOT ispat OR largest < n)" if p.c3 else ""
        clash = f"SELECT c.fid, f.fid AS old, f.endc FROM cand{h} c JOIN f{h - 1} f ON f.sup = c.sup AND list_contains(c.pre, f.fid)" if p.c2 else "SELECT ''::VARCHAR AS fid, ''::VARCHAR AS old, false AS endc WHERE false"
        out.append(f"cand{h} AS MATERIALIZED (SELECT * FROM (SELECT * FROM c{h} WHERE NOT ispat UNION ALL SELECT * FROM s{h}) WHERE n >= {p.l_min}{high} {c3})")
        out.append(f"clash{h} AS MATERIALIZED ({clash})")
        out.append(f"sel{h} AS MATERIALIZED (SELECT * FROM cand{h} WHERE fid NOT IN (SELECT fid FROM clash{h}) OR (NOT isc AND fid IN (SELECT fid FROM clash{h} WHERE endc)))")
        out.append(f"f{h} AS MATERIALIZED (SELECT fid, len, ispat, n, sup, endc FROM f{h - 1} WHERE fid NOT IN (SELECT old FROM clash{h} SEMI JOIN sel{h} USING (fid)) UNION ALL SELECT fid, {h}, ispat, n, sup, isc FROM sel{h})")
        out.append(f"dep{h} AS MATERIALIZED (SELECT pid, fid, ps, es, ispat, pre FROM x{h} SEMI JOIN s{h} USING (fid))")
        go_on = f"len(ss) >= {p.l_min} OR pid IN (SELECT pid FROM dep{h})" if p.prune else "true"
        out.append(f"next{h} AS MATERIALIZED (SELECT * FROM p{h} WHERE {go_on})")
        out.append(f"g{h} AS MATERIALIZED (SELECT pid, fid, ps, es, ispat, pre FROM x{h} WHERE NOT ispat UNION ALL SELECT * FROM dep{h})")
    kinds = [k for k in ("path", "pattern") if k in p.kinds]
    out.append(f"found AS MATERIALIZED (SELECT fid AS feature, CASE WHEN ispat THEN 'pattern' ELSE 'path' END AS kind, len, n FROM f{p.k} WHERE CASE WHEN ispat THEN 'pattern' ELSE 'path' END IN ({', '.join(repr(k) for k in kinds) or repr('')}))")
    return out


def neighbours(view: str, seed: str, p: MiningParams) -> str:
    return with_(base(view, seed, p), "SELECT v AS vertex, n AS support FROM near")


def class_supports(view: str, seed: str, p: MiningParams) -> str:
    return with_(base(view, seed, p), "SELECT cls AS class, n AS support FROM tsup SEMI JOIN tf USING (cls)")


def features(view: str, seed: str, p: MiningParams, near: bool = True) -> str:
    own = "SELECT v AS feature, 'neighbour' AS kind, 0 AS len, n AS support FROM near UNION ALL " if near and "neighbour" in p.kinds else ""
    return with_(base(view, seed, p) + mining(p), own + "SELECT feature, kind, len, n AS support FROM found")


def ladder(view: str, seed: str, p: MiningParams, after_m: list[str] | None = None) -> str:
    gen = " + ".join(f"(SELECT count(*) FROM c{h})" for h in range(1, p.k + 1))
    rows = {
        "neighbours_before": "SELECT count(*) FROM rv",
        "classes_before": "SELECT count(DISTINCT cls) FROM lev",
        "neighbours_after": "SELECT count(*) FROM near",
        "classes_after": "SELECT count(*) FROM tf",
        "generated": f"SELECT {gen}",
        "selected": "SELECT count(*) FROM found",
    }
    if after_m:
        rows |= {"neighbours_after_m": "SELECT count(*) FROM near_m", "selected_after_m": "SELECT count(*) FROM found_m"}
    body = " UNION ALL ".join(f"SELECT '{k}' AS stage, ({v})::BIGINT AS n" for k, v in rows.items())
    return with_(base(view, seed, p) + mining(p) + (after_m or []), body)
