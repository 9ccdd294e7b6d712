"""The kernel as functions for DataFrames and SQL; items are names, with an in-memory hierarchy
of bounded size."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..plans.transducers import compile_expression
from .kernel import Kernel


class NamedKernel:
    """Expression over named items. ``edges``: (child, parent) pairs."""

    def __init__(self, expression: str, edges=(), match: str = "anywhere") -> None:
        self.t, self.parents = compile_expression(expression, match), {}
        for c, p in edges:
            self.parents.setdefault(c, []).append(p)
        self.ids: dict[str, int] = {}
        self.names: list[str] = []
        self.up: dict[int, tuple[int, ...]] = {}
        self.kernel = Kernel(self.t, self.up, self.ids)

    def number(self, w: str) -> int:
        if w not in self.ids:
            self.ids[w] = len(self.names)
            self.names.append(w)
            above = dict.fromkeys(a for p in self.parents.get(w, ()) for a in self.up[self.number(p)])
            self.up[self.ids[w]] = (self.ids[w], *above)
        return self.ids[w]

    def outputs(self, items) -> list[list[str]]:
        for w in self.t.names:
            self.number(w)
        return sorted([self.names[a] for a in o] for o in self.kernel.generate([self.number(w) for w in items]))

    def accepts(self, items) -> bool:
        for w in self.t.names:
            self.number(w)
        return self.kernel.accepts([self.number(w) for w in items])


def seq_accepts(expression: str, edges=(), match: str = "anywhere"):
    """Function: whether a sequence has an accepting run."""

    @F.pandas_udf("boolean")
    def accepts(items: pd.Series) -> pd.Series:
        k = NamedKernel(expression, edges, match)
        return items.map(lambda x: None if x is None else k.accepts(x))

    return accepts


def seq_outputs(expression: str, edges=(), match: str = "anywhere"):
    """Function: the outputs of a sequence, each once."""

    @F.pandas_udf("array<array<string>>")
    def outputs(items: pd.Series) -> pd.Series:
        k = NamedKernel(expression, edges, match)
        return items.map(lambda x: None if x is None else k.outputs(x))

    return outputs


def seq_contains(edges=()):
    """Function of (sequence, pattern): whether the pattern is a generalised subsequence."""

    @F.pandas_udf("boolean")
    def contains(items: pd.Series, pattern: pd.Series) -> pd.Series:
        k = NamedKernel("(.^)", edges)

        def one(seq, pat) -> bool:
            at = 0
            for w in seq:
                if at < len(pat) and k.number(pat[at]) in k.up[k.number(w)]:
                    at += 1
            return at == len(pat)

        return pd.Series([None if a is None or b is None else one(a, b) for a, b in zip(items, pattern, strict=True)])

    return contains


def register_sql(spark: SparkSession, edges=()) -> None:
    """Table function ``seq_patterns(items, expression, match)`` for use with LATERAL."""
    edges = list(edges)

    class SeqPatterns:
        def eval(self, items: list, expression: str, match: str):
            for o in NamedKernel(expression, edges, match).outputs(items or []):
                yield (o,)

    spark.udtf.register("seq_patterns", F.udtf(SeqPatterns, returnType="pattern array<string>"))
