"""Functions in Python, for what has no built-in form: a cosine on Arrow batches and a table function that lists a template's relaxations."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf(T.DoubleType())  # types as objects: a string would need a session at import
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two vectors of one length; null if either is null or has length zero."""

    def one(x, y):
        if x is None or y is None:
            return None
        x, y = np.asarray(x, np.float64), np.asarray(y, np.float64)
        size = np.sqrt((x @ x) * (y @ y))
        return float(x @ y / size) if size else None

    return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="object").astype("Float64")


@udtf(returnType=T.StructType([T.StructField("level", T.IntegerType()), T.StructField("variant", T.IntegerType()), T.StructField("edges", T.StringType())]))
class Relaxations:
    """Every connected template that is left when 0 to ``most`` edges go, level by level."""

    def eval(self, template: str, most: int):
        from graphsieve.plans.template import Template

        t = Template.from_json(template)
        for level in range(most + 1):
            for k, x in enumerate(t.relaxations(level)):
                yield level, k, " ".join(f"{a}-{b}" for a, b in x.edges)


@pandas_udf(T.DoubleType())
def jaccard(own: pd.Series, other: pd.Series) -> float:
    """Grouped: how alike two columns of a group are as sets; nulls are left out, two empty sets are alike."""
    a, b = set(own.dropna()), set(other.dropna())
    return len(a & b) / len(a | b) if a | b else 1.0


def bucketed_labels(frames):
    """For mapInPandas: ``(vid, label)`` with the kind of the vertex split from its label."""
    for f in frames:
        parts = f["label"].str.partition(":")
        yield pd.DataFrame({"vid": f["vid"], "kind": parts[0], "detail": parts[2]})


def triangles_of(frame: pd.DataFrame) -> pd.DataFrame:
    """For applyInPandas: a component's edges ``(component, src, dst)``, both ways, to its number of triangles, by backtracking."""
    near: dict[int, set[int]] = {}
    for a, b in zip(frame["src"], frame["dst"]):
        near.setdefault(a, set()).add(b)
    n = sum(1 for a in near for b in near[a] if a < b for c in near[a] & near[b] if b < c)
    return pd.DataFrame({"component": [frame["component"].iloc[0]], "triangles": [n]})
