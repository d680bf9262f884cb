"""Read-only checkers: code is read-only only if every part of it matches an allowed rule."""

from __future__ import annotations

import ast
from dataclasses import dataclass, field

# The default allowlist.
FUNCTIONS = {"print", "sum", "len", "min", "max", "abs", "round", "sorted", "range", "str", "int", "float", "bool", "repr", "type", "isinstance", "zip", "enumerate", "any", "all", "list", "tuple", "dict", "set"}
METHODS = {"head", "tail", "describe", "info", "count", "mean", "std", "var", "median", "sum", "min", "max", "nunique", "unique", "copy", "keys", "values", "items", "get", "index", "upper", "lower", "strip", "split", "join", "startswith", "endswith", "format", "show", "printSchema", "explain", "select", "where", "filter", "groupBy", "agg", "limit", "collect", "first", "take", "isEmpty"}
#: Types whose methods of these names are known not to change them.
TYPES = {"str", "int", "float", "bool", "bytes", "tuple", "list", "dict", "set", "frozenset", "DataFrame", "Column", "ndarray", "Series", "NoneType", "range"}
NODES = (
    ast.Module, ast.Expr, ast.Expression, ast.Name, ast.Load, ast.Constant, ast.Attribute, ast.Subscript, ast.Slice, ast.Tuple, ast.List, ast.Set, ast.Dict, ast.BinOp, ast.UnaryOp, ast.BoolOp, ast.Compare, ast.IfExp,
    ast.JoinedStr, ast.FormattedValue, ast.Call, ast.keyword, ast.operator, ast.unaryop, ast.boolop, ast.cmpop, ast.Starred, ast.Pass,
)


@dataclass
class RuleSet:
    functions: set[str] = field(default_factory=lambda: set(FUNCTIONS))
    methods: set[str] = field(default_factory=lambda: set(METHODS))
    types: set[str] = field(default_factory=lambda: set(TYPES))

    def add(self, function: str | None = None, method: str | None = None, type_: str | None = None) -> RuleSet:
        for group, name in ((self.functions, function), (self.methods, method), (self.types, type_)):
            if name:
                group.add(name)
        return self


def is_read_only(code: str, names: dict | None = None, rules: RuleSet | None = None) -> tuple[bool, str]:
    """(verdict, reason). names: the live namespace; it refines rules by run-time types and finds shadowed built-ins."""
    rules, names = rules or RuleSet(), names or {}
    try:
        tree = ast.parse(code)
    except SyntaxError as e:
        return False, f"not parsed: {e.msg}"
    for node in ast.walk(tree):
        if not isinstance(node, NODES):
            return False, f"{type(node).__name__} is not allowed"
        if isinstance(node, ast.Name | ast.Attribute | ast.Subscript) and not isinstance(node.ctx, ast.Load):
            return False, "assignment"
        if isinstance(node, ast.Call) and (why := _call(node, names, rules)):
            return False, why
        if isinstance(node, ast.Attribute) and (why := _attribute(node, names, rules)):
            return False, why
        if isinstance(node, ast.Subscript) and isinstance(node.value, ast.Name) and not _plain(node.value.id, names, rules):
            return False, f"subscript of {node.value.id}, whose type is not known"
    return True, "every part is allowed"


def _plain(name: str, names: dict, rules: RuleSet) -> bool:
    return name in names and type(names[name]).__name__ in rules.types


def _call(node: ast.Call, names: dict, rules: RuleSet) -> str:
    if any(k.arg in ("inplace", "out", "file") or k.arg is None for k in node.keywords):
        return "a keyword that may write"
    f = node.func
    if isinstance(f, ast.Name):
        if f.id in names:
            return f"{f.id} is shadowed or user-defined"
        return "" if f.id in rules.functions else f"function {f.id} is not allowed"
    if isinstance(f, ast.Attribute):
        return "" if f.attr in rules.methods else f"method {f.attr} is not allowed"
    return "a computed callee"


def _attribute(node: ast.Attribute, names: dict, rules: RuleSet) -> str:
    root = node.value
    if isinstance(root, ast.Name) and not _plain(root.id, names, rules):
        return f"attribute of {root.id}, whose type is not known"
    return "a private attribute" if node.attr.startswith("_") else ""


# Logical plan nodes that only read.
READ_PLANS = {"Project", "Filter", "Aggregate", "Sort", "Distinct", "Join", "SubqueryAlias", "UnresolvedRelation", "UnresolvedSubqueryColumnAliases", "GlobalLimit", "LocalLimit", "Union", "Except", "Intersect", "UnresolvedHaving", "WithCTE", "UnresolvedWith", "OneRowRelation", "UnresolvedInlineTable", "Window", "WithWindowDefinition", "Pivot", "UnresolvedHint", "LateralJoin", "Generate", "Sample", "Offset", "GroupingSets", "Range", "UnresolvedTableValuedFunction", "LocalRelation", "ExplainCommand"}


def is_read_only_sql(spark, sql: str) -> tuple[bool, str]:
    """From the parsed plan: every node must be one that reads."""
    try:
        plan = spark._jsparkSession.sessionState().sqlParser().parsePlan(sql)
    except Exception as e:
        return False, f"not parsed: {str(e)[:60]}"
    stack = [plan]
    while stack:
        node = stack.pop()
        if node.nodeName() not in READ_PLANS:
            return False, f"{node.nodeName()} is not allowed"
        children = node.children()
        stack += [children.apply(i) for i in range(children.size())]
    return True, "every plan node reads"
