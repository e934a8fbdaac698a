"""Answers in responses: boxed expressions, LaTeX to plain text, safe arithmetic, exact
comparison of expressions. Parsing that needs a stack runs in Arrow batches; everything
else is built-in expressions."""

from __future__ import annotations

import ast
import math
import re
from fractions import Fraction
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

# The unit tokens that resolve.
UNITS = ("m", "s", "kg", "g", "N", "J", "W", "K", "A", "V", "C", "Pa", "Hz", "T", "mol", "rad", "cm", "mm", "km", "ms", "min", "h", "kJ", "kW", "eV", "MeV", "ohm", "F", "H", "L", "nm", "kPa")
_BRACE = re.compile(r"\\boxed\{|[{}]")


def boxes(text: str | None) -> list[str]:
    """Complete boxed expressions in order of their start, blank ones left out; an
    unclosed box is none. One pass over the braces."""
    found: list[tuple[int, str]] = []
    open_at: list[tuple[int, bool]] = []
    for m in _BRACE.finditer(text or ""):
        if m[0] != "}":
            open_at.append((m.end(), m[0] != "{"))
        elif open_at:
            start, box = open_at.pop()
            if box and text[start : m.start()].strip():
                found.append((start, text[start : m.start()].strip()))
    return [x for _, x in sorted(found)]


@F.pandas_udf(T.ArrayType(T.StringType()))
def all_boxed(text: pd.Series) -> pd.Series:
    return text.map(boxes)


@F.pandas_udf(T.StringType())
def last_boxed(text: pd.Series) -> pd.Series:
    return text.map(lambda t: (boxes(t) or [None])[-1])


def tail(text: Column, n: int = 600) -> Column:
    """The last n characters."""
    return F.when(F.length(text) > n, F.substring(text, -n, n)).otherwise(text)


def tail_numbers(text: Column, n: int = 300) -> Column:
    return F.regexp_extract_all(tail(text, n), F.lit(r"-?[0-9]+(?:\.[0-9]+)?"), F.lit(0))


def to_plain(x: Column) -> Column:
    """LaTeX of flat expressions to arithmetic: wrappers dropped, fractions to quotients
    (two levels), products to *, pi to a name."""
    for _ in range(2):
        x = F.regexp_replace(x, r"\\(?:text|mathrm)\{([^{}]*)\}", "$1")
        x = F.regexp_replace(x, r"\\[dt]?frac\{([^{}]*)\}\{([^{}]*)\}", "($1)/($2)")
        x = F.regexp_replace(x, r"\\sqrt\{([^{}]*)\}", "sqrt($1)")
    x = F.regexp_replace(x, r"\\(?:times|cdot)", "*")
    x = F.regexp_replace(x, r"\\pi", "pi")
    return F.trim(F.regexp_replace(x, r"\\[,;! ]|\$", ""))


def plain_text(x: str) -> str:
    """LaTeX as arithmetic: wrappers and sizes dropped, fractions to quotients at any depth,
    products to *, braced exponents in parentheses, commas of thousands out."""
    x = re.sub(r"\\(?:left|right)\b|\\[,;!: ]|\{,\}|\\?%|\$", "", x)
    before = None
    while before != x:
        before = x
        x = re.sub(r"\\(?:text|mathrm|mathbf|textbf)\{([^{}]*)\}", r"\1", x)
        x = re.sub(r"\\[dt]?frac\{([^{}]*)\}\{([^{}]*)\}", r"((\1)/(\2))", x)
        x = re.sub(r"\\sqrt\{([^{}]*)\}", r"sqrt(\1)", x)
        x = re.sub(r"\^\{([^{}]*)\}", r"^(\1)", x)
    x = re.sub(r"(?<=[0-9]),(?=[0-9]{3}(?![0-9]))", "", x)
    return re.sub(r"\\(?:times|cdot)\b", "*", x).replace("\\pi", "pi").strip()


# -- expressions

_NAMES = {"pi": math.pi}
_CALLS = {"sqrt": math.sqrt, "sin": math.sin, "cos": math.cos, "tan": math.tan, "exp": math.exp, "log": math.log}


def _tree(x: str):
    x = re.sub(r"(?<=[0-9)])\s*(?=[a-zA-Z(])", "*", x.replace("^", "**"))
    return ast.parse(x.strip(), mode="eval").body


def _value(node, names: dict[str, float]) -> float:
    """Value of an expression of the allowed shapes; anything else raises."""
    if isinstance(node, ast.Constant) and type(node.value) in (int, float):
        return float(node.value)
    if isinstance(node, ast.Name):
        return names[node.id]
    if isinstance(node, ast.UnaryOp) and isinstance(node.op, (ast.USub, ast.UAdd)):
        v = _value(node.operand, names)
        return -v if isinstance(node.op, ast.USub) else v
    if isinstance(node, ast.BinOp):
        a, b = _value(node.left, names), _value(node.right, names)
        if isinstance(node.op, ast.Add):
            return a + b
        if isinstance(node.op, ast.Sub):
            return a - b
        if isinstance(node.op, ast.Mult):
            return a * b
        if isinstance(node.op, ast.Div):
            return a / b
        if isinstance(node.op, ast.Pow) and abs(b) <= 64:
            v = a**b
            if isinstance(v, float):
                return v
    if isinstance(node, ast.Call) and isinstance(node.func, ast.Name) and len(node.args) == 1 and not node.keywords:
        return _CALLS[node.func.id](_value(node.args[0], names))
    raise ValueError("not an allowed expression")


#: A unit at the end: letters, and what powers and quotients of units are written with. An
#: exponent after a digit is part of the number.
_UNIT = re.compile(r"\s*(?!(?<=[0-9.])[eE][-+]?[0-9])(?:[A-Za-z]+[0-9^()\-]*[\s*/]*)+$")


def evaluate(x: str | None) -> float | None:
    """Number of an arithmetic text (plain or LaTeX, behind an equals sign, before a unit), else
    of its numeric prefix, else none."""
    if not x or len(x) > 500:
        return None
    plain = plain_text(x).rpartition("=")[2]
    for text in (plain, _UNIT.sub("", plain)):
        try:
            v = _value(_tree(text), _NAMES)
            return v if math.isfinite(v) else None
        except (ValueError, SyntaxError, KeyError, ZeroDivisionError, OverflowError, TypeError, RecursionError, MemoryError):
            continue
    m = re.match(r"\s*(-?[0-9]+(?:\.[0-9]+)?(?:[eE][-+]?[0-9]+)?)", plain)
    return float(m[1]) if m else None


@F.pandas_udf(T.DoubleType())
def evaluated(x: pd.Series) -> pd.Series:
    return x.map(evaluate).astype(float)


def number_of(x: Column) -> Column:
    """Plain numbers by a cast in codegen; only what is left goes to the arithmetic reader.
    Spark runs a pandas UDF for all rows of a projection, so it gets null for the others."""
    cast = x.try_cast("double")
    return F.coalesce(cast, evaluated(F.when(cast.isNull(), x)))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def all_evaluated(parts: pd.Series) -> pd.Series:
    return parts.map(lambda xs: None if xs is None else [evaluate(x) for x in xs])


def numbers_of(parts: Column) -> Column:
    """Numbers of an array of texts by the whole ladder: a cast in codegen, and for arrays of
    which a text is no plain number the arithmetic reader."""
    cast = F.transform(parts, lambda x: x.try_cast("double"))
    return F.coalesce(all_evaluated(F.when(F.exists(cast, lambda v: v.isNull()), parts)), cast)


Poly = dict[tuple[tuple[str, int], ...], Fraction]


def _times(a: Poly, b: Poly) -> Poly:
    out: Poly = {}
    for m, x in a.items():
        for n, y in b.items():
            powers: dict[str, int] = dict(m)
            for v, k in n:
                powers[v] = powers.get(v, 0) + k
            key = tuple(sorted((v, k) for v, k in powers.items() if k))
            out[key] = out.get(key, Fraction(0)) + x * y
    return {k: v for k, v in out.items() if v}


def _plus(a: Poly, b: Poly, sign: int = 1) -> Poly:
    out = dict(a)
    for k, v in b.items():
        out[k] = out.get(k, Fraction(0)) + sign * v
    return {k: v for k, v in out.items() if v}


def _ratio(node) -> tuple[Poly, Poly]:
    """Exact numerator and denominator of a rational expression in any variables."""
    one: Poly = {(): Fraction(1)}
    if isinstance(node, ast.Constant) and type(node.value) in (int, float):
        v = Fraction(str(node.value))
        return ({(): v} if v else {}), one
    if isinstance(node, ast.Name):
        return {((node.id, 1),): Fraction(1)}, one
    if isinstance(node, ast.UnaryOp) and isinstance(node.op, (ast.USub, ast.UAdd)):
        n, d = _ratio(node.operand)
        return (_plus({}, n, -1) if isinstance(node.op, ast.USub) else n), d
    if isinstance(node, ast.BinOp):
        (a, b), (c, d) = _ratio(node.left), _ratio(node.right) if not isinstance(node.op, ast.Pow) else (one, one)
        if isinstance(node.op, (ast.Add, ast.Sub)):
            return _plus(_times(a, d), _times(c, b), 1 if isinstance(node.op, ast.Add) else -1), _times(b, d)
        if isinstance(node.op, ast.Mult):
            return _times(a, c), _times(b, d)
        if isinstance(node.op, ast.Div) and c:
            return _times(a, d), _times(b, c)
        if isinstance(node.op, ast.Pow):
            k = node.right.operand if (neg := isinstance(node.right, ast.UnaryOp) and isinstance(node.right.op, ast.USub)) else node.right
            if isinstance(k, ast.Constant) and isinstance(k.value, int) and 0 <= k.value <= 12:
                n, m = one, one
                for _ in range(k.value):
                    n, m = _times(n, a), _times(m, b)
                if not neg:
                    return n, m
                if n:
                    return m, n
    raise ValueError("not a rational expression")


@lru_cache(maxsize=50_000)
def equivalent(p: str, g: str) -> bool | None:
    """Do two expressions agree? Exact for rational ones; by value at fixed points where
    functions occur; None where neither can tell (counted as different, and flagged)."""
    if p.strip() == g.strip():
        return True
    try:
        a, b = _tree(plain_text(p)), _tree(plain_text(g))
    except (SyntaxError, ValueError, RecursionError, MemoryError):
        return None
    try:
        (n, d), (m, e) = _ratio(a), _ratio(b)
        return not _plus(_times(n, e), _times(m, d), -1)
    except (ValueError, RecursionError):
        pass
    names = sorted({x.id for t in (a, b) for x in ast.walk(t) if isinstance(x, ast.Name)} - set(_NAMES) - set(_CALLS))
    agree = 0
    for k in range(1, 6):
        point = {**_NAMES, **{v: 0.37 * k + 0.61 * (i + 1) for i, v in enumerate(names)}}
        try:
            x, y = _value(a, point), _value(b, point)
        except (ValueError, KeyError, ZeroDivisionError, OverflowError, TypeError):
            continue
        if abs(x - y) > 1e-9 * max(1.0, abs(x), abs(y)):
            return False
        agree += 1
    return True if agree >= 3 else None


@F.pandas_udf(T.BooleanType())
def symbolic_match(p: pd.Series, g: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else equivalent(x, y) for x, y in zip(p, g, strict=True)], dtype=object)


def readable(x: str) -> bool:
    try:
        _tree(plain_text(x))
        return bool(x.strip())
    except (SyntaxError, ValueError, RecursionError, MemoryError):
        return False


_FRAC = re.compile(r"\\frac\{([^{}]*)\}\{([^{}]*)\}")


@F.pandas_udf(T.BooleanType())
def has_readable_fraction(text: pd.Series) -> pd.Series:
    return text.map(lambda t: any(readable(a) and readable(b) for a, b in _FRAC.findall(t or "")))


def unit_tokens(text: Column) -> Column:
    """Letters right after a number."""
    return F.regexp_extract_all(text, F.lit(r"[0-9](?:\.[0-9]+)?\s?([A-Za-z]+)\b"), F.lit(1))


# -- match ladder


def match_letter(pred: Column, gold: Column) -> Column:
    """Do two texts choose the same letter? Wrappers go first; a letter counts where no other
    letter follows it: B, (B), \\text{B} and B) Paris."""

    def letter(c: Column) -> Column:
        bare = F.regexp_replace(c, r"\\(?:text|mathrm|mathbf|textbf)\{([^{}]*)\}", "$1")
        return F.upper(F.regexp_extract(bare, r"^[^A-Za-z]*([A-Za-z])(?![A-Za-z])", 1))

    return F.coalesce((letter(pred) == letter(gold)) & (letter(gold) != ""), F.lit(False))


def close(p: Column, g: Column, tol: float) -> Column:
    """|p - g| <= tol |g|; a gold of zero wants |p| <= 1e-9; no number never agrees."""
    return F.coalesce(F.when(F.isnan(p) | F.isnan(g), False).when(g == 0, F.abs(p) <= 1e-9).otherwise(F.abs(p - g) <= tol * F.abs(g) + 1e-12), F.lit(False))


_THOUSANDS = r"(?<=[0-9]),(?=[0-9]{3}(?![0-9]))"


def parts_of(answer: Column, wanted: Column | None = None) -> Column:
    """Parts of an answer between semicolons and commas. A comma between a digit and exactly
    three others is one of thousands, unless cutting there too gives as many parts as are
    ``wanted``."""
    bare = F.regexp_replace(answer, r"\{,\}|\\[,;!: ]", "")
    aware = F.transform(F.split(bare, r";|,(?![0-9]{3}(?![0-9]))|(?<![0-9]),"), lambda x: F.trim(F.regexp_replace(x, _THOUSANDS, "")))
    if wanted is None:
        return aware
    every = F.transform(F.split(bare, r"[;,]"), lambda x: F.trim(x))
    return F.when(F.size(every) == wanted, every).otherwise(aware)
