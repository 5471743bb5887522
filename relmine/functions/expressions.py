"""Expression trees of arithmetic and string rules, compiled to Columns."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import Column
from pyspark.sql import functions as F

ARITHMETIC = ("+", "-", "*", "/")
Tree = tuple | str


def leaves(tree: Tree) -> list[str]:
    """Columns of a tree, left to right."""
    if isinstance(tree, str):
        return [tree]
    if tree[0] == "lit":
        return []
    return [c for part in tree[1:] if isinstance(part, (tuple, str)) and not _is_option(tree[0], part) for c in leaves(part)]


def _is_option(op: str, part) -> bool:
    return isinstance(part, tuple) and part[:1] == ("opt",)


def _options(tree: tuple) -> list:
    return [p[1] for p in tree[1:] if _is_option(tree[0], p)]


def opt(value) -> tuple:
    """A constant argument of an operator, such as a delimiter."""
    return ("opt", value)


def evaluate(tree: Tree, column: Callable[[str], Column] = F.col) -> Column:
    """The tree as a Column; ``column`` says where a leaf's value comes from."""
    if isinstance(tree, str):
        return column(tree)
    op, args = tree[0], [p for p in tree[1:] if not _is_option(tree[0], p)]
    if op == "lit":
        return F.lit(tree[1])
    v, o = [evaluate(a, column) for a in args], _options(tree)
    if op in ARITHMETIC:
        a, b = v
        # a result that the type cannot hold is null, as division by zero is
        return F.try_add(a, b) if op == "+" else F.try_subtract(a, b) if op == "-" else F.try_multiply(a, b) if op == "*" else F.try_divide(a.cast("double"), b.cast("double"))
    text = [x.cast("string") for x in v]
    if op == "concat":
        return F.concat(*text)
    if op == "token":  # delimiter, place from 1; from the right if negative
        return F.element_at(F.split(text[0], _literal(o[0])), F.lit(o[1])) if o[1] == 1 else F.get(F.split(text[0], _literal(o[0])), F.lit(o[1] - 1)) if o[1] > 0 else F.try_element_at(F.split(text[0], _literal(o[0])), F.lit(o[1]))
    if op == "slice":
        return F.substring(text[0], o[0], o[1])
    if op == "after":
        return F.when(F.instr(text[0], o[0]) > 0, F.regexp_replace(text[0], "^.*?" + _literal(o[0]), ""))
    if op == "before":
        return F.substring_index(text[0], o[0], 1)
    if op == "padded":
        return F.when(F.length(text[0]) >= o[0], text[0]).otherwise(F.lpad(text[0], o[0], "0"))
    simple = {"lower": F.lower, "upper": F.upper, "trim": F.trim, "length": F.length}
    if op in simple:
        return simple[op](text[0])
    if op == "mod":
        return F.pmod(v[0], F.lit(o[0]))
    if op == "affine":  # a * x + b
        return F.try_add(F.try_multiply(v[0], F.lit(o[0])), F.lit(o[1]))
    raise ValueError(f"unknown operator {op}")


def divides(tree: Tree | None) -> bool:
    """Whether a division stands in the tree, so that its value is no whole number."""
    return isinstance(tree, tuple) and (tree[0] == "/" or any(divides(part) for part in tree[1:] if not _is_option(tree[0], part)))


def _literal(text: str) -> str:
    return "".join("\\" + c if c in r"\.[]{}()*+-?^$|" else c for c in text)


def render(tree: Tree) -> str:
    if isinstance(tree, str):
        return tree
    op, args, o = tree[0], [p for p in tree[1:] if not _is_option(tree[0], p)], _options(tree)
    if op == "lit":
        return f"'{tree[1]}'"
    if op in ARITHMETIC:
        return f"({render(args[0])} {op} {render(args[1])})"
    return f"{op}({', '.join([*map(render, args), *map(repr, o)])})"


def sql_text(tree: Tree) -> str:
    """The tree in SQL that Spark and other engines read alike; columns must have plain names."""
    if isinstance(tree, str):
        return tree
    op, args, o = tree[0], [p for p in tree[1:] if not _is_option(tree[0], p)], _options(tree)
    if op == "lit":
        return "'" + tree[1].replace("'", "''") + "'"
    v = [sql_text(a) for a in args]
    if op == "/":
        return f"(cast({v[0]} as double) / nullif({v[1]}, 0))"
    if op in ARITHMETIC:
        return f"({v[0]} {op} {v[1]})"
    if op == "concat":
        return f"concat({', '.join(v)})"
    if op == "token":
        return f"split_part({v[0]}, '{o[0]}', {o[1]})"
    if op == "slice":
        return f"substr({v[0]}, {o[0]}, {o[1]})"
    if op == "padded":
        return f"lpad(cast({v[0]} as varchar(64)), {o[0]}, '0')"
    if op == "mod":
        return f"({v[0]} % {o[0]})"
    if op == "affine":
        return f"({o[0]} * {v[0]} + {o[1]})"
    if op in ("lower", "upper", "trim", "length"):
        return f"{op}({v[0]})"
    raise ValueError(f"no SQL for {op}")


def signed_sum(tree: Tree, sign: int = 1) -> dict[str, int] | None:
    """Sign of each leaf of a rule of + and - only; None for others."""
    if isinstance(tree, str):
        return {tree: sign}
    if tree[0] not in ("+", "-"):
        return None
    a, b = signed_sum(tree[1], sign), signed_sum(tree[2], sign if tree[0] == "+" else -sign)
    return None if a is None or b is None else a | b


def canonical(tree: Tree) -> Tree:
    """One tree for all that differ by the order of sums and products."""
    if isinstance(tree, str) or tree[0] not in ARITHMETIC:
        return tree
    signs = signed_sum(tree)
    if signs is not None:
        plus, minus = sorted(c for c, s in signs.items() if s > 0), sorted(c for c, s in signs.items() if s < 0)
        if plus:
            out: Tree = plus[0]
            for c in plus[1:]:
                out = ("+", out, c)
            for c in minus:
                out = ("-", out, c)
            return out
    a, b = canonical(tree[1]), canonical(tree[2])
    if tree[0] in ("+", "*") and render(b) < render(a):
        a, b = b, a
    return (tree[0], a, b)


def subtrees(tree: Tree) -> Iterator[Tree]:
    """Inner nodes, the root last."""
    if isinstance(tree, tuple) and tree[0] in ARITHMETIC:
        for part in tree[1:]:
            yield from subtrees(part)
        yield tree


def absorbed_above(tree: Tree, node: Tree) -> bool:
    """Whether a factor between ``node`` and the root could hide a changed value of the node (a zero)."""
    if tree == node or isinstance(tree, str):
        return False
    for part, other in ((tree[1], tree[2]), (tree[2], tree[1])):
        if node == part or node in list(subtrees(part)):
            return tree[0] in ("*", "/") or absorbed_above(part, node)
    return False
