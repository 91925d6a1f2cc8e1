"""The oracle: the same methods as recursive SQL for DuckDB, over the fixtures' own SELECTs."""

from __future__ import annotations

from kgfold.config import IntegrationConfig
from kgfold.plans.fixtures import FIXTURES, SEEDS


def ctes(name: str, cfg: IntegrationConfig | None = None) -> list[tuple[str, str]]:
    """Every stage as a named SELECT, in order of dependence."""
    cfg = cfg or IntegrationConfig(seed=SEEDS[name])
    seed = cfg.seed
    rel = ", ".join(f"('{r}', {rank})" for r, _, rank in cfg.relation_rows())
    order = "CASE source " + " ".join(f"WHEN '{s}' THEN {i}" for i, s in enumerate(cfg.order)) + " ELSE 999999 END, " if cfg.order else ""
    cls_limit = f" AND cls < {cfg.active_classes}" if cfg.active_classes is not None else ""
    to_seed = f" AND split_part(dst, ':', 1) = '{seed}'" if cfg.targets == "seed" else ""
    unique = "" if cfg.ambiguous == "least" else "WHERE lo = hi"
    agreed = "" if cfg.obsolete_ambiguous == "least" else "HAVING min(dst) = max(dst)"
    internal = {"all": "WHERE ss <> ds", "used": "WHERE NOT EXISTS (SELECT 1 FROM fwd WHERE fwd.src = m.src AND fwd.dst = m.dst)", "keep": ""}[cfg.internal_links]
    aligned = "UNION SELECT src, dst FROM elect" if cfg.align else ""
    same = " AND split_part(a, ':', 1) <> split_part(b, ':', 1)" if cfg.same_source == "edge" else ""
    tree = "SELECT child, parent FROM hier"
    if cfg.hierarchies is not None:
        tree += " WHERE split_part(child, ':', 1) IN (" + ", ".join(f"'{h}'" for h in cfg.hierarchies) + ")"
    if cfg.same_source == "edge":
        tree += " UNION SELECT a, b FROM chosen WHERE a <> b AND split_part(a, ':', 1) = split_part(b, ':', 1)"
    start = "SELECT sid, node, 0 FROM marks WHERE node IN (SELECT concept FROM anchors)" if cfg.path == "any_anchor" else "SELECT sid, node, 0 FROM roots"
    return [
        *FIXTURES[name],
        ("rel(relation, cls)", f"VALUES {rel}"),
        ("ranks", f"SELECT source, row_number() OVER (ORDER BY (source <> '{seed}'), {order}n DESC, source) - 1 AS rnk FROM (SELECT source, count(*) AS n FROM concept GROUP BY source)"),
        ("ml", "SELECT src, mapping.relation AS relation, dst, cls, split_part(src, ':', 1) AS ss, split_part(dst, ':', 1) AS ds FROM mapping JOIN rel ON mapping.relation = rel.relation"),
        ("obs", "SELECT concept FROM concept WHERE is_obsolete"),
        ("fwd", f"SELECT src, min(dst) AS dst FROM ml WHERE cls = 0 AND ss = ds AND src IN (SELECT concept FROM obs) AND dst NOT IN (SELECT concept FROM obs) GROUP BY src {agreed}"),
        ("moved", f"SELECT DISTINCT coalesce(a.dst, m.src) AS src, m.relation AS relation, coalesce(b.dst, m.dst) AS dst, cls FROM ml m LEFT JOIN fwd a ON m.src = a.src LEFT JOIN fwd b ON m.dst = b.src {internal}"),
        ("links", "SELECT * FROM moved WHERE src <> dst"),
        ("ori", "SELECT src, dst, cls FROM links UNION SELECT dst, src, cls FROM links"),
        ("sides", f"SELECT ori.*, rnk FROM ori JOIN ranks ON source = split_part(dst, ':', 1) WHERE split_part(src, ':', 1) <> '{seed}'{cls_limit}{to_seed}"),
        ("cand", "SELECT src, cls, rnk, min(dst) AS lo, max(dst) AS hi FROM sides GROUP BY src, cls, rnk"),
        ("elect", f"SELECT src, lo AS dst, cls, rnk FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY cls, rnk) AS rn FROM cand {unique}) WHERE rn = 1"),
        ("merges", f"SELECT src, dst FROM fwd {aligned}"),
        ("und", "SELECT src AS a, dst AS b FROM merges UNION SELECT dst, src FROM merges"),
        ("clo(a, b)", "SELECT a, b FROM und UNION SELECT a, a FROM und UNION SELECT clo.a, und.b FROM clo JOIN und ON clo.b = und.a"),
        ("chosen", "SELECT a, b FROM (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY coalesce(is_obsolete, false), coalesce(rnk, 999999), b) AS rn FROM clo LEFT JOIN concept ON concept = b LEFT JOIN ranks ON ranks.source = split_part(b, ':', 1)) WHERE rn = 1"),
        ("can", f"SELECT a AS src, b AS dst FROM chosen WHERE a <> b{same}"),
        ("dconcept", "SELECT DISTINCT coalesce(dst, concept) AS concept, split_part(coalesce(dst, concept), ':', 1) AS source FROM concept LEFT JOIN can ON concept = src"),
        ("dmapping", "SELECT DISTINCT coalesce(a.dst, l.src) AS src, l.relation AS relation, coalesce(b.dst, l.dst) AS dst FROM links l LEFT JOIN can a ON l.src = a.src LEFT JOIN can b ON l.dst = b.src WHERE coalesce(a.dst, l.src) <> coalesce(b.dst, l.dst)"),
        ("unm", "SELECT concept, source FROM concept WHERE NOT is_obsolete AND concept NOT IN (SELECT src FROM can)"),
        ("tree", tree),
        ("sedge", f"SELECT DISTINCT coalesce(a.dst, child) AS child, coalesce(b.dst, parent) AS parent FROM tree LEFT JOIN can a ON child = a.src LEFT JOIN can b ON parent = b.src WHERE split_part(child, ':', 1) = '{seed}' AND coalesce(a.dst, child) <> coalesce(b.dst, parent)"),
        ("anchors", f"SELECT child AS concept FROM tree WHERE split_part(child, ':', 1) = '{seed}' UNION SELECT parent FROM tree WHERE split_part(child, ':', 1) = '{seed}' UNION SELECT src FROM can WHERE split_part(dst, ':', 1) = '{seed}'"),
        ("frag", f"SELECT DISTINCT split_part(child, ':', 1) AS sid, child, parent FROM tree WHERE split_part(child, ':', 1) <> '{seed}'"),
        ("marks", "SELECT sid, child AS node FROM frag UNION SELECT sid, parent FROM frag"),
        ("roots", "SELECT DISTINCT sid, parent AS node FROM frag f WHERE NOT EXISTS (SELECT 1 FROM frag g WHERE g.sid = f.sid AND g.child = f.parent)"),
        ("bfs(sid, node, dist)", f"{start} UNION SELECT f.sid, f.child, bfs.dist + 1 FROM bfs JOIN frag f ON f.sid = bfs.sid AND f.parent = bfs.node WHERE bfs.dist < 60"),
        ("far", "SELECT sid, node, min(dist) AS dist FROM bfs GROUP BY sid, node"),
        ("hop", "SELECT f.sid AS sid, f.child AS node, d.dist AS dist, min(f.parent) AS nxt FROM frag f JOIN far d ON d.sid = f.sid AND d.node = f.child JOIN far e ON e.sid = f.sid AND e.node = f.parent AND e.dist = d.dist - 1 GROUP BY f.sid, f.child, d.dist"),
        ("walk(sid, start, pos, k)", "SELECT hop.sid, hop.node, hop.nxt, 1 FROM hop JOIN unm ON concept = hop.node AND source = hop.sid UNION ALL SELECT walk.sid, walk.start, hop.nxt, k + 1 FROM walk JOIN hop ON hop.sid = walk.sid AND hop.node = walk.pos"),
        ("seen", "SELECT sid, start, pos, k, pos IN (SELECT concept FROM anchors) AS is_a, EXISTS (SELECT 1 FROM unm WHERE concept = pos AND source = sid) AS is_o FROM walk"),
        ("att", "SELECT start AS child, arg_min(pos, k) FILTER (WHERE is_a OR is_o) AS up FROM seen WHERE start NOT IN (SELECT concept FROM anchors) GROUP BY sid, start HAVING bool_or(is_a)"),
        ("atte", "SELECT DISTINCT child, coalesce(dst, up) AS parent FROM att LEFT JOIN can ON up = src"),
        ("dtree", "SELECT child, parent FROM sedge UNION SELECT child, parent FROM atte"),
        ("bucket", f"SELECT c.concept AS concept, CASE WHEN can.dst IS NULL AND c.source = '{seed}' THEN 'seed' WHEN can.dst IS NOT NULL AND split_part(can.dst, ':', 1) = '{seed}' THEN 'to_seed' WHEN can.dst IS NOT NULL THEN 'to_other' WHEN c.is_obsolete THEN 'obsolete_open' ELSE 'unmapped' END AS bucket, c.concept IN (SELECT child FROM atte) AS attached FROM concept c LEFT JOIN can ON c.concept = can.src"),
    ]


def sql(name: str, last: str, cfg: IntegrationConfig | None = None, extra: list[tuple[str, str]] = ()) -> str:
    """``last`` over the stages it needs."""
    chain = [*ctes(name, cfg), *extra]
    heads = {h.split("(")[0]: q for h, q in chain}
    wanted, todo = set(), [last]
    import re

    while todo:
        for word in set(re.findall(r"\w+", todo.pop())) & set(heads):
            if word not in wanted:
                wanted.add(word)
                todo.append(heads[word])
    body = ", ".join(f"{h} AS ({q})" for h, q in chain if h.split("(")[0] in wanted)
    return f"WITH RECURSIVE {body} {last}"


def components_of(edges: str, a: str, b: str, tag: str) -> list[tuple[str, str]]:
    """Named SELECTs that end in ``{tag}_label(node, label)``: least node of each component (by repeated closure)."""
    return [
        (f"{tag}_e", f"SELECT {a} AS x, {b} AS y FROM {edges} UNION SELECT {b}, {a} FROM {edges}"),
        (f"{tag}_c(x, y)", f"SELECT x, x FROM {tag}_e UNION SELECT {tag}_e.y, {tag}_c.y FROM {tag}_c JOIN {tag}_e ON {tag}_c.x = {tag}_e.x WHERE {tag}_c.y < {tag}_e.y"),
        (f"{tag}_label", f"SELECT x AS node, min(y) AS label FROM {tag}_c GROUP BY x"),
    ]
