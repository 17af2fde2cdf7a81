"""SQL names for the measures: Arrow-batched functions, a path-unfolding table function, and a grouped aggregate."""

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """jaccard(a, b), soergel_set(a, b), soergel(fa, va, fb, vb), ebf(n, d), recall_of(got, want), path_hops(nodes, steps)."""

    def sets(a, b):
        return [1.0 if not len(x) and not len(y) else len(set(x) & set(y)) / len(set(x) | set(y)) for x, y in zip(a, b)]

    @F.pandas_udf("double")
    def jaccard(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(sets(a, b))

    @F.pandas_udf("double")
    def soergel_set(a: pd.Series, b: pd.Series) -> pd.Series:
        return 1.0 - pd.Series(sets(a, b))

    @F.pandas_udf("double")
    def soergel(fa: pd.Series, va: pd.Series, fb: pd.Series, vb: pd.Series) -> pd.Series:
        out = []
        for a, x, b, y in zip(fa, va, fb, vb):
            p, q = dict(zip(a, x)), dict(zip(b, y))
            small = sum(min(v, q[f]) for f, v in p.items() if f in q)
            top = sum(p.values()) + sum(q.values()) - small
            out.append(1.0 - small / top if top else 0.0)
        return pd.Series(out)

    @F.pandas_udf("double")
    def ebf(n: pd.Series, d: pd.Series) -> pd.Series:
        out = []
        for total, depth in zip(n, d):
            lo, hi = 0.0, float(max(total, 1))
            for _ in range(60):
                x, s = (lo + hi) / 2, 0.0
                for _ in range(int(depth)):
                    s = (s + 1) * x
                lo, hi = (x, hi) if s < total else (lo, x)
            out.append((lo + hi) / 2 if depth > 0 and total > 0 else None)
        return pd.Series(out, dtype="float64")

    @F.pandas_udf("double")
    def recall_of(hit: pd.Series) -> float:
        return float(hit.mean()) if len(hit) else 1.0

    @F.udtf(returnType="hop int, a bigint, b bigint, dist double")
    class PathHops:
        def eval(self, nodes, steps):
            for i, (a, b) in enumerate(zip(nodes[:-1], nodes[1:])):
                yield i + 1, a, b, steps[i]

    for name, f in (("jaccard", jaccard), ("soergel_set", soergel_set), ("soergel", soergel), ("ebf", ebf), ("recall_of", recall_of)):
        spark.udf.register(name, f)
    spark.udtf.register("path_hops", PathHops)
