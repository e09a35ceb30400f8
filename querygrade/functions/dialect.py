"""Bridge from PostGIS-style statements to Spark SQL: operator forms of spatial predicates and ``::`` casts as functions.

The parsed tree tells where each operator and its two sides stand in the text; only these places are rewritten, the
rest of the statement stays as it was written.  A statement without such forms comes back unchanged, and so does a
translated one.
"""

from __future__ import annotations

from querygrade.functions.sqlscan import Node, parse

#: Function of each spatial operator.
OPERATORS = {"&&": "ST_BBoxOverlaps", "~=": "ST_BBoxSame", "<->": "ST_Distance", "@": "ST_BBoxWithin", "~": "ST_BBoxContains"}
#: Spark's names of types that it calls otherwise; '' leaves the value as it is.
TYPES = {"text": "string", "varchar": "string", "character varying": "string", "float8": "double", "double precision": "double", "float4": "float", "int2": "smallint", "int4": "int", "int8": "bigint", "bool": "boolean", "numeric": "decimal(38,18)", "timestamptz": "timestamp", "geometry": "", "geography": ""}


def _places(root: Node, text: str) -> list[tuple[int, int, Node]]:
    """Spans to rewrite, outer before inner."""
    out, stack = [], [root]
    while stack:
        node = stack.pop()
        stack.extend(node.kids)
        if node.kind == "operator" and node.text in OPERATORS and len(node.kids) == 2:
            out.append((*node.span, node))
        elif node.kind == "cast" and node.kids and text[node.kids[0].span[1] : node.span[1]].lstrip().startswith("::"):
            out.append((*node.span, node))
    return sorted(out, key=lambda x: (x[0], -x[1]))


def to_spark_sql(text: str) -> str:
    """``text`` in Spark's terms; raises SyntaxFault where it is no statement of the grammar.

    ``~`` before a string literal is a match of a regular expression, else containment of boxes.
    """
    places = _places(parse(text), text)

    def written(low: int, high: int, skip: Node | None = None) -> str:
        out, at = [], low
        for a, b, node in places:
            if node is skip or a < at or b > high or a >= high:
                continue
            out += [text[at:a], changed(node)]
            at = b
        return "".join([*out, text[at:high]])

    def changed(node: Node) -> str:
        sides = [written(*k.span, skip=None if (k.span != node.span) else node) for k in node.kids[:2]]
        if node.kind == "cast":
            kind = TYPES.get(node.text.lower(), node.text)
            return f"CAST({sides[0]} AS {kind})" if kind else sides[0]
        if node.text == "~" and node.kids[1].kind == "literal" and not node.kids[1].text[:1].isdigit():
            return f"regexp_like({sides[0]}, {sides[1]})"
        return f"{OPERATORS[node.text]}({sides[0]}, {sides[1]})"

    return written(0, len(text))
