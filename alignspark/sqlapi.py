"""SQL functions and table functions over the alignment kernels."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .functions.scoring import Scoring
from .operators import kernels as K


def register(spark: SparkSession) -> None:
    """align_score(a, b, match, mismatch, gap), aligned(a, b, match, mismatch, gap), consensus(aligned), all_optimal(...), align_family(...)."""

    @F.pandas_udf("long")
    def align_score(a: pd.Series, b: pd.Series, m: pd.Series, x: pd.Series, g: pd.Series) -> pd.Series:
        frame = pd.DataFrame({"a": a, "b": b, "m": m, "x": x, "g": g})
        out = pd.Series(0, index=frame.index, dtype="int64")
        for (mm, xx, gg), part in frame.groupby(["m", "x", "g"]):
            out[part.index] = K.scores(list(zip(part["a"], part["b"])), Scoring(int(mm), int(xx), int(gg)))
        return out

    @F.pandas_udf("aligned_a string, aligned_b string")
    def aligned(a: pd.Series, b: pd.Series, m: pd.Series, x: pd.Series, g: pd.Series) -> pd.DataFrame:
        rows = [K.spell(p, q, K.align_moves(p, q, Scoring(int(mm), int(xx), int(gg)))[0]) for p, q, mm, xx, gg in zip(a, b, m, x, g)]
        return pd.DataFrame(rows, columns=["aligned_a", "aligned_b"])

    @F.pandas_udf("string")
    def consensus(rows: pd.Series) -> str:
        strings = [r for r in rows if r is not None]
        if not strings:
            return ""
        symbols, codes = K.coded(strings, K.GAP)
        counts = sum((pd.get_dummies(pd.Categorical(c, range(len(symbols)))).to_numpy(dtype="int64") for c in codes))
        return "".join(symbols[k] for k in K.consensus(counts, symbols, "first", 0, "", 0))

    @F.udtf(returnType="k int, aligned_a string, aligned_b string")
    class AllOptimal:
        def eval(self, a: str, b: str, m: int, x: int, g: int, limit: int):
            for k, (p, q) in enumerate(K.all_optimal(a, b, Scoring(m, x, g), limit)):
                yield k, p, q

    @F.udtf(returnType="place int, aligned string")
    class AlignFamily:
        def eval(self, seqs: list, method: str):
            from .operators.progressive import build_tree

            s = Scoring.experiment()
            strings = list(seqs)
            rows = strings if len(strings) == 1 else K.progressive(strings, build_tree(K.distance_matrix(strings, "mismatch_gap", s), method), K.Options(scoring=s))[0]
            yield from enumerate(rows)

    spark.udf.register("align_score", align_score)
    spark.udf.register("aligned", aligned)
    spark.udf.register("consensus_of", consensus)
    spark.udtf.register("all_optimal", AllOptimal)
    spark.udtf.register("align_family", AlignFamily)
