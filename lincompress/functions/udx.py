"""What Spark lacks as built-ins: macros, tails as UDFs, a grouped UDF and a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from lincompress.functions import tails


def suff_stats(column: str | Column) -> Column:
    """struct(cnt, sy, syy): a macro over built-in sums, so partial aggregation stays."""
    c = F.col(column) if isinstance(column, str) else column
    c = c.cast("double")
    return F.struct(F.count(c).alias("cnt"), F.sum(c).alias("sy"), F.sum(c * c).alias("syy"))


def logistic_prob(eta: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-eta))


@F.pandas_udf(T.DoubleType())
def norm_cdf(x: pd.Series) -> pd.Series:
    return x.map(tails.norm_cdf)


@F.pandas_udf(T.DoubleType())
def t_sf(t: pd.Series, df: pd.Series) -> pd.Series:
    return pd.Series([tails.t_sf(a, b) for a, b in zip(t, df, strict=True)])


def gram_agg():
    """Grouped pandas UDF: packed Gram of an array column with weights."""

    @F.pandas_udf("array<double>")
    def gram(x: pd.Series, w: pd.Series) -> list:
        import numpy as np

        m = np.vstack(x.to_list())
        g = (m * w.to_numpy()[:, None]).T @ m
        return g[np.triu_indices(len(g))].tolist()

    return gram


class FitLinear:
    """Table function over a compressed frame (columns cnt, sy_<y>, syy_<y> and features): coefficient rows."""

    def __init__(self):
        self.rows, self.formula, self.cov = [], None, None

    def eval(self, row, formula: str, cov: str):
        self.rows.append(row.asDict())
        self.formula, self.cov = formula, cov

    def terminate(self):
        import numpy as np

        from lincompress.operators.solve import inverse_spd

        if not self.rows:
            return
        y, right = (s.strip() for s in self.formula.split("~"))
        names = ["(intercept)", *[s.strip() for s in right.split("+")]]
        x = np.array([[1.0, *[float(r[n]) for n in names[1:]]] for r in self.rows])
        n, s, q = (np.array([float(r[c]) for r in self.rows]) for c in ("cnt", f"sy_{y}", f"syy_{y}"))
        bread = inverse_spd((x * n[:, None]).T @ x)
        beta = bread @ (x.T @ s)
        fit = x @ beta
        rss = n * fit**2 - 2 * fit * s + q
        cov = bread * rss.sum() / (n.sum() - len(beta)) if self.cov != "ehw" else bread @ ((x * rss[:, None]).T @ x) @ bread
        for name, b, v in zip(names, beta, np.diag(cov), strict=True):
            yield name, float(b), float(np.sqrt(v))


def register_all(spark: SparkSession) -> None:
    """SQL names: norm_cdf, t_sf, and fit_linear(TABLE(cf) WITH SINGLE PARTITION, 'y ~ a + b', 'ehw')."""
    spark.udf.register("norm_cdf", norm_cdf)
    spark.udf.register("t_sf", t_sf)
    spark.udtf.register("fit_linear", F.udtf(FitLinear, returnType="term string, coef double, se double"))
