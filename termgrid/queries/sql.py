"""DuckDB twins of plans, by full joins: independent of counting."""

from __future__ import annotations

from collections.abc import Sequence

from ..catalog import SchemaGraph, orders_schema
from ..plans.networks import Node

GRAPH = orders_schema()


def tokens(text: str) -> str:
    return rf"list_filter(regexp_split_to_array(lower({text}), '[^\p{{L}}\p{{N}}_#]+'), lambda t: t <> '')"


def view(name: str, graph: SchemaGraph = GRAPH) -> str:
    r = graph.relations[name]
    joins = "".join(f" join {t} on {own} = {key}" for t, own, key in r.merge)
    return f"(select {', '.join(r.keys)}, {tokens('concat_ws(' + chr(39) + ' ' + chr(39) + ', ' + ', '.join(r.text) + ')')} as terms from {r.source()}{joins})"


def tuple_set(name: str, keywords: Sequence[str], mask: int) -> str:
    tests = " and ".join(f"{'' if mask >> i & 1 else 'not '}list_contains(terms, '{w}')" for i, w in enumerate(keywords))
    return f"(select * from {view(name)} where {tests or 'true'})"


def results(node: Node, keywords: Sequence[str]) -> str:
    """All results with one bag, by a full join."""
    froms, bags, n = "", [], 0

    def visit(x: Node, parent: str) -> None:
        nonlocal froms, n
        me = f"n{n}"
        n += 1
        bags.append(f"{me}.terms")
        froms += f" from {tuple_set(x.relation, keywords, x.mask)} {me}" if not parent else f" join {tuple_set(x.relation, keywords, x.mask)} {me} on {parent}.{x.on[0]} = {me}.{x.on[1]}"
        for c in x.children:
            visit(c, me)

    visit(node, "")
    return f"select flatten([{', '.join(bags)}]) as terms{froms}"


def result_tuples(node: Node, keywords: Sequence[str], graph: SchemaGraph = GRAPH) -> str:
    """All results by the relation and keys of their rows."""
    names = [f"concat_ws(':', '{x.relation}', " + ", ".join(f"n{i}.{k}" for k in graph.relations[x.relation].keys) + ")" for i, x in enumerate(node.walk())]
    text = results(node, keywords)
    return f"select list_sort([{', '.join(names)}]) as tuples" + text[text.index(" from ", text.index(" as terms")) :]


def without(keywords: Sequence[str]) -> str:
    return " where term not in (" + ", ".join(f"'{w}'" for w in keywords) + ")" if keywords else ""


def frequencies(nodes: Sequence[Node], keywords: Sequence[str], drop: bool = True) -> str:
    union = " union all ".join(results(n, keywords) for n in nodes)
    return f"select term, count(*)::bigint as freq from (select unnest(terms) as term from ({union}) r) u{without(keywords if drop else ())} group by term"


def top(freq: str, k: int) -> str:
    return f"select term, freq, row_number() over (order by freq desc, term)::bigint as rank from ({freq}) f qualify rank <= {k}"


def batch(queries: Sequence[tuple[int, list[str]]], make) -> str:
    """Top ten of every query of a batch."""
    each = " union all ".join(f"select {q}::int as qid, term, freq from ({frequencies([make()], kw)}) f{q}" for q, kw in queries)
    return f"select qid, term, freq, row_number() over (partition by qid order by freq desc, term)::bigint as rank from ({each}) e qualify rank <= 10"
