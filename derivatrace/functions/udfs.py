"""Functions for packaged polynomials, where built-ins don't reach; none is on a hot path."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.plans.cq import BLANK
from derivatrace.plans.ontology import Ontology
from derivatrace.plans.rewrite import atom_closure

POLY = T.ArrayType(T.ArrayType(T.StringType()))


@F.pandas_udf(POLY)
def simplify_minimal(polys: pd.Series) -> pd.Series:
    """Only the monomials that contain no other one."""

    def one(poly):
        sets = sorted({frozenset(m) for m in poly}, key=len)
        kept: list[frozenset] = []
        for m in sets:
            if not any(k <= m for k in kept):
                kept.append(m)
        return sorted(sorted(m) for m in kept)

    return polys.map(one, na_action="ignore")


@F.pandas_udf(POLY)
def multiply_general(left: pd.Series, right: pd.Series) -> pd.Series:
    """Product of two packaged polynomials at the general level, coefficients as repeats."""

    def one(a, b):
        return sorted(sorted((Counter(x) + Counter(y)).elements()) for x in a for y in b)

    return pd.Series([None if a is None or b is None else one(a, b) for a, b in zip(left, right, strict=True)])


def register_derivations(spark: SparkSession, ontology: Ontology, name: str = "derivations") -> None:
    """A table function derivations(sub, super): one row for the label set of each way from one concept to another."""
    axioms = list(ontology.positive)

    class Derivations:
        def eval(self, sub: str, sup: str) -> Iterator[tuple[str]]:
            for (p, q), ways in atom_closure(sup, (("h", "x"),), axioms).items():
                if p == sub and BLANK not in q and len(q) == 1:
                    for w in sorted(ways):
                        yield ("*".join(w),)

    spark.udtf.register(name, F.udtf(Derivations, returnType="labels string"))
