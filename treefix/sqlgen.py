"""The same predicates and rules as DuckDB SQL: the other side of the correctness check."""

from __future__ import annotations

import re

from treefix.rules import Const, Program, Rule
from treefix.sources.tables import EVENT_TYPES, GAP
from treefix.workloads import SEEDS

_SIGNS = "'{k}:' || array_to_string(list_transform(list_slice(embedding, 8 * {k} + 1, 8 * {k} + 8), lambda x: CASE WHEN x >= 0 THEN '1' ELSE '0' END), '')"

_LINES = "(SELECT CAST(o_custkey AS BIGINT) AS c, CAST(l_partkey AS BIGINT) AS p, CAST(l_suppkey AS BIGINT) AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
_HANDOFF = "(SELECT event_type, CAST(user_id AS BIGINT) AS u, CAST(lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS BIGINT) AS v FROM events)"


def _big(**columns: str) -> str:
    return ", ".join(f"CAST({source} AS BIGINT) AS {name}" for name, source in columns.items())


#: SQL of each predicate; the sets come from SELECT DISTINCT
TABLES = {
    "LivesIn": f"SELECT DISTINCT {_big(c='c_custkey', n='c_nationkey')} FROM customer",
    "Segment": f"SELECT DISTINCT {_big(c='c_custkey')}, c_mktsegment AS g FROM customer",
    "BasedIn": f"SELECT DISTINCT {_big(s='s_suppkey', n='s_nationkey')} FROM supplier",
    "InRegion": f"SELECT DISTINCT {_big(n='n_nationkey', r='n_regionkey')} FROM nation",
    "RegionName": f"SELECT DISTINCT {_big(r='r_regionkey')}, r_name AS x FROM region",
    "Placed": f"SELECT DISTINCT {_big(c='o_custkey', o='o_orderkey')} FROM orders",
    "Status": f"SELECT DISTINCT {_big(o='o_orderkey')}, o_orderstatus AS x FROM orders",
    "Priority": f"SELECT DISTINCT {_big(o='o_orderkey')}, o_orderpriority AS x FROM orders",
    "Line": f"SELECT DISTINCT {_big(o='l_orderkey', p='l_partkey', s='l_suppkey')} FROM lineitem",
    "Supplies": f"SELECT DISTINCT {_big(s='l_suppkey', p='l_partkey')} FROM lineitem",
    "Bought": f"SELECT DISTINCT c, p FROM {_LINES}",
    "BoughtFrom": f"SELECT DISTINCT c, s FROM {_LINES}",
    "HasBrand": f"SELECT DISTINCT {_big(p='p_partkey')}, p_brand AS b FROM part",
    "HasType": f"SELECT DISTINCT {_big(p='p_partkey')}, p_type AS t FROM part",
    "HasSize": f"SELECT DISTINCT {_big(p='p_partkey', z='p_size')} FROM part",
    "Did": f"SELECT DISTINCT {_big(u='user_id')}, event_type AS t FROM events",
    "NextTurn": "SELECT DISTINCT CAST(a.conv_id AS BIGINT) AS k, CAST(a.turn AS BIGINT) AS x, CAST(b.turn AS BIGINT) AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "Role": f"SELECT DISTINCT {_big(k='conv_id', x='turn')}, role AS r FROM conversations",
    "OnHost": f"SELECT DISTINCT {_big(g='page_id')}, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS h FROM pages",
    "PageLang": f"SELECT DISTINCT {_big(g='page_id')}, regexp_extract(url, '^[a-z]+://[^/]+/([^/]*)', 1) AS l FROM pages",
    "LinksTo": f"SELECT DISTINCT {_big(g='page_id')}, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages",
    "DocFrom": f"SELECT DISTINCT {_big(d='doc_id')}, source AS s FROM documents",
    "DocLang": f"SELECT DISTINCT {_big(d='doc_id')}, lang AS l FROM documents",
    "HasLine": "SELECT DISTINCT d, md5(line) AS f FROM (SELECT CAST(doc_id AS BIGINT) AS d, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20",
    "Mentions": "SELECT DISTINCT CAST(doc_id AS BIGINT) AS d, CAST(item_id AS BIGINT) AS i FROM documents JOIN benchmark b ON length(b.text) > 0 AND contains(documents.text, b.text)",
    "Quality": f"SELECT DISTINCT {_big(d='doc_id', q='quality')} FROM labels",
    "Toxic": f"SELECT DISTINCT {_big(d='doc_id', x='toxic')} FROM labels",
    "InBucket": f"SELECT DISTINCT CAST(vec_id AS BIGINT) AS v, unnest([{', '.join(_SIGNS.format(k=k) for k in range(4))}]) AS x FROM embeddings",
    "HasLabel": f"SELECT DISTINCT {_big(v='vec_id', l='label')} FROM embeddings",
}
for _t in EVENT_TYPES:
    TABLES[f"Handoff_{_t}"] = f"SELECT DISTINCT u, v FROM {_HANDOFF} WHERE event_type = '{_t}' AND v IS NOT NULL AND u <> v"
    TABLES[f"Forward_{_t}"] = f"{TABLES[f'Handoff_{_t}']} AND u < v AND v - u <= {{gap}}"
TABLES["Forward_any"] = f"SELECT DISTINCT u, v FROM {_HANDOFF} WHERE v IS NOT NULL AND u < v AND v - u <= {{gap}}"
#: Column names of each predicate, in order of its arguments
_NAMES = "LivesIn c n, Segment c g, BasedIn s n, InRegion n r, RegionName r x, Placed c o, Status o x, Priority o x, Line o p s, Supplies s p, Bought c p, BoughtFrom c s, HasBrand p b, HasType p t, HasSize p z, Did u t, NextTurn k x y, Role k x r, OnHost g h, PageLang g l, LinksTo g t, DocFrom d s, DocLang d l, HasLine d f, Mentions d i, Quality d q, Toxic d x, InBucket v x, HasLabel v l"
COLUMNS = {n.split()[0]: n.split()[1:] for n in _NAMES.split(", ")} | {p: ["u", "v"] for p in TABLES if p.startswith(("Handoff", "Forward"))}


def facts_cte(pred: str, where: str = "", gap: int = GAP) -> str:
    """A predicate as a table expression with columns a0, a1 ..."""
    names = COLUMNS[pred]
    columns = ", ".join(f"a{n}" for n in range(len(names)))
    return f'"{pred}"({columns}) AS (SELECT * FROM ({TABLES[pred].format(gap=gap)}) t({columns}) {where})'


def md5_of(pred: str, arity: int) -> str:
    return f"md5(concat_ws('|', '{pred}', {', '.join(f'CAST(a{n} AS VARCHAR)' for n in range(arity))}))"


def rule_select(rule: Rule, table_of=lambda n, pred: f'"{pred}"', names: list[str] | None = None, count: str = "") -> str:
    """The heads of a rule as one SELECT over tables with columns a0, a1 ..."""
    where, place = [], {}
    sources = []
    for n, atom in enumerate(rule.body):
        sources.append(f"{table_of(n, atom.pred)} t{n}")
        for k, t in enumerate(atom.terms):
            here = f"t{n}.a{k}"
            if isinstance(t, Const):
                where.append(f"{here} = " + ("'" + t.value.replace("'", "''") + "'" if isinstance(t.value, str) else str(t.value)))
            elif t.name in place:
                where.append(f"{here} = {place[t.name]}")
            else:
                place[t.name] = here

    def put(text: str) -> str:
        return re.sub(r"\b[A-Za-z_]\w*\b(?!\s*\()", lambda m: place.get(m[0], m[0]), text)

    for b in rule.builtins:
        if hasattr(b, "var"):
            place[b.var] = f"({put(b.text)})"
        else:
            where.append(put(b.text))
    out = [("'" + t.value + "'" if isinstance(t.value, str) else str(t.value)) if isinstance(t, Const) else place[t.name] for t in rule.head.terms]
    names = names or [f"a{n}" for n in range(len(out))]
    columns = ", ".join(f"{o} AS {n}" for o, n in zip(out, names)) or "TRUE AS flag_"
    text = f"SELECT {'' if count else 'DISTINCT '}{columns}{count} FROM {', '.join(sources)}"
    return text + (f" WHERE {' AND '.join(where)}" if where else "") + (f" GROUP BY {', '.join(out)}" if count else "")


def seeds_select(pred: str) -> str:
    source, cols = SEEDS[pred]
    at = [COLUMNS[source].index(c) for c in cols]
    return f"SELECT DISTINCT {', '.join(f'a{i} AS a{n}' for n, i in enumerate(at))} FROM \"{source}\""


def _ordered(program: Program) -> list[list[Rule]]:
    from treefix.rules import stratify

    return [list(layer) for layer in stratify(program)]


def program_ctes(program: Program, where: dict[str, str] | None = None, seeds: dict[str, str] | None = None, extra: dict[str, str] | None = None) -> str:
    """All predicates of a program as table expressions: given ones, then derived ones in layers. A recursive
    predicate is a keyed recursion over all its columns, which reads all it has derived so far, also twice in a rule.

    ``where``: a filter of a given predicate. ``seeds``: SQL of explicit facts of derived ones. ``extra``: table expressions of given predicates that no table carries."""
    where, extra = where or {}, extra or {}
    derived = program.derived
    parts = [*extra.values()]
    given = {a.pred for r in program.rules for a in r.body if a.pred not in derived} | {SEEDS[p][0] for p in derived if p in SEEDS and not (seeds and p in seeds)}
    for p in sorted(given - set(extra)):
        parts.append(facts_cte(p, where.get(p, "")))
    for layer in _ordered(program):
        heads = {r.head.pred for r in layer}
        assert len(heads) == 1, "mutual recursion has no SQL here"
        pred = heads.pop()
        arity = len(layer[0].head.terms)
        columns = ", ".join(f"a{n}" for n in range(arity))
        start = [rule_select(r) for r in layer if pred not in {a.pred for a in r.body}]
        if seeds and pred in seeds:
            start.append(seeds[pred])
        elif pred in SEEDS:
            start.append(seeds_select(pred))
        loops = [r for r in layer if pred in {a.pred for a in r.body}]
        first = " UNION ".join(f"({s})" for s in start)
        if not loops:
            parts.append(f'"{pred}"({columns}) AS ({first})')
            continue
        steps = " UNION ".join(f"({rule_select(r, lambda n, p, own=pred: f'recurring.' + chr(34) + p + chr(34) if p == own else chr(34) + p + chr(34))})" for r in loops)
        fresh = f'SELECT * FROM ({steps}) s ANTI JOIN recurring."{pred}" k USING ({columns})'
        parts.append(f'"{pred}"({columns}) USING KEY ({columns}) AS ({first} UNION {fresh})')
    return "WITH RECURSIVE " + ",\n".join(parts)


def counts_sql(program: Program, preds: list[str], **options) -> str:
    """A row for each predicate: its name and how many facts it has."""
    rows = " UNION ALL ".join(f"SELECT '{p}' AS pred, CAST(count(*) AS BIGINT) AS facts FROM \"{p}\"" for p in preds)
    return f"{program_ctes(program, **options)}\n{rows}"


def facts_sql(program: Program, pred: str, names: list[str], **options) -> str:
    columns = ", ".join(f"a{n} AS {v}" for n, v in enumerate(names))
    return f'{program_ctes(program, **options)}\nSELECT {columns} FROM "{pred}"'
