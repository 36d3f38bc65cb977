"""The signals as SQL functions, so that pipelines can be written in SQL; bodies inline into the plan."""

from __future__ import annotations

from pyspark.sql import SparkSession

_FUNCTIONS = {
    "implicit_margin": ("pw BIGINT, pl BIGINT, rw BIGINT, rl BIGINT", "DOUBLE", "((pw - rw) - (pl - rl)) / 1000000D"),
    "polarity_gap": ("pw BIGINT, pl BIGINT, iw BIGINT, il BIGINT", "DOUBLE", "((pw - pl) - (iw - il)) / 1000000D"),
    "polarity_label": ("gap DOUBLE, tau DOUBLE", "INT", "CASE WHEN gap IS NULL OR isnan(gap) THEN NULL WHEN abs(gap) > tau THEN CAST(sign(gap) AS INT) ELSE 0 END"),
    "avg_nll": ("lp BIGINT, n INT", "DOUBLE", "try_divide(-lp / 1000000D, CAST(n AS DOUBLE))"),
    "nll_gap": ("rw BIGINT, nw INT, rl BIGINT, nl INT", "DOUBLE", "try_divide(-rw / 1000000D, CAST(nw AS DOUBLE)) - try_divide(-rl / 1000000D, CAST(nl AS DOUBLE))"),
    "ppl": ("lp BIGINT, n INT", "DOUBLE", "exp(try_divide(-lp / 1000000D, CAST(n AS DOUBLE)))"),
}


def register_sql(spark: SparkSession) -> None:
    for name, (args, kind, body) in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")


def register_expand_pair(spark: SparkSession) -> None:
    """``expand_pair(chosen, rejected)``: side, position, token and the one before, as a table function."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="side string, pos int, tok string, prev string")
    class ExpandPair:
        def eval(self, chosen: str, rejected: str):
            import re

            for side, text in (("w", chosen), ("l", rejected)):
                before = ""
                for pos, tok in enumerate(x for x in re.split("[ \n\t\r]+", text or "") if x):
                    yield side, pos, tok, before
                    before = tok

    spark.udtf.register("expand_pair", ExpandPair)
