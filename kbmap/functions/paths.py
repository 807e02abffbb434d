"""Property paths: parsing, printing, inverting; terms of facts as Spark columns."""

from __future__ import annotations

import re
from typing import NamedTuple

from pyspark.sql import Column
from pyspark.sql import functions as F


class Step(NamedTuple):
    prop: str
    inv: bool = False


Path = tuple[Step, ...]


def invert_path(path: Path) -> Path:
    return tuple(Step(s.prop, not s.inv) for s in reversed(path))


def parse_path(text: str) -> list[Path]:
    """The alternatives of a path text with ``/``, ``^``, ``|`` and parentheses."""
    tokens = re.findall(r"[A-Za-z_][\w:.-]*|[/^|()]", text)
    if "".join(tokens) != re.sub(r"\s", "", text):
        raise ValueError(f"not a path: {text!r}")
    at = 0

    def peek():
        return tokens[at] if at < len(tokens) else None

    def take(expected=None):
        nonlocal at
        token = peek()
        if token is None or expected and token != expected:
            raise ValueError(f"not a path: {text!r}")
        at += 1
        return token

    def unit() -> list[Path]:
        token = take()
        if token == "^":
            return [invert_path(p) for p in unit()]
        if token == "(":
            inner = choice()
            take(")")
            return inner
        if token in "/|)":
            raise ValueError(f"not a path: {text!r}")
        return [(Step(token),)]

    def chain() -> list[Path]:
        paths = unit()
        while peek() == "/":
            take()
            paths = [p + q for q_list in [unit()] for p in paths for q in q_list]
        return paths

    def choice() -> list[Path]:
        paths = chain()
        while peek() == "|":
            take()
            paths = paths + chain()
        return paths

    found = choice()
    if peek() is not None:
        raise ValueError(f"not a path: {text!r}")
    return found


def render_path(path: Path) -> str:
    return "/".join(("^" if s.inv else "") + s.prop for s in path)


def iri(kind: str, *keys) -> Column:
    """``kind/key`` (several keys joined by a dot); null if a key is null."""
    parts = [F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in keys]
    joined = parts[0]
    for p in parts[1:]:
        joined = F.concat(joined, F.lit("."), p)
    return F.concat(F.lit(f"{kind}/"), joined)


def lexical(value: Column, kind: str) -> Column:
    """The text of a literal, the same in every engine: doubles with two decimals, timestamps to the second."""
    if kind in ("double", "float"):
        return value.cast("decimal(18,2)").cast("string")
    if kind.startswith("timestamp"):
        return F.date_format(value, "yyyy-MM-dd HH:mm:ss")
    return value.cast("string")


def skolem(label: str, keys: list[Column], hashed: bool = False) -> Column:
    """An invented node: a term over the values that make it one node; null if any of them is."""
    term = F.lit(f"_:{label}(")
    for i, k in enumerate(keys):
        term = F.concat(term, F.lit("," if i else ""), k)
    term = F.concat(term, F.lit(")"))
    return F.concat(F.lit("_:"), F.sha2(term, 256)) if hashed else term
