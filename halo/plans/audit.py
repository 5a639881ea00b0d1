"""What a plan moves: exchanges, those of observations, and the physical text."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def own_lines(df: DataFrame) -> list[str]:
    """Plan lines without those of tables that are cached already, nor a plan shown a second time."""
    out, hidden = [], None
    for line in physical(df).split("== Initial Plan ==")[0].split("\n"):
        depth = len(line) - len(line.lstrip(" :+-*()0123456789"))
        if hidden is not None and depth > hidden:
            continue
        hidden = depth if "InMemoryRelation" in line else None
        out.append(line)
    return out


def exchanges(df: DataFrame) -> int:
    """Shuffles in the physical plan (broadcasts not counted)."""
    return sum(bool(re.search(r"(?<!Broadcast)(?<!Reused)Exchange (?:hash|range|round|single)", line, re.I)) for line in own_lines(df))


def observation_exchanges(df: DataFrame) -> int:
    """Shuffles that do not carry partial aggregates, so move observations."""
    lines, n = own_lines(df), 0
    for k, line in enumerate(lines):
        if re.search(r"(?<!Broadcast)Exchange (hash|range|round|single)", line, re.I):
            below = next((x for x in lines[k + 1 :] if not re.search(r"WholeStage|InputAdapter", x)), "")
            n += "partial_" not in below and "functions=[]" not in below
    return n


def pushed(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: (\[[^\]]*\])", physical(df))


def row(name: str, value: float, config: str = "") -> tuple[str, float, str]:
    return (name, float(value), config)
