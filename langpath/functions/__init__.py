"""SQL functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def register(spark: SparkSession) -> None:
    """``lp_accepts(expression, words)`` and the table functions ``lp_transitions(expression)`` and
    ``lp_machine(rules)``, usable in lateral joins."""
    @pandas_udf("boolean")
    def accepts(expression: pd.Series, words: pd.Series) -> pd.Series:
        from langpath.language import fsm

        machines: dict[str, fsm.Fsm] = {}
        out = []
        for e, w in zip(expression, words, strict=True):
            if e is None or w is None:
                out.append(None)
                continue
            if e not in machines:
                machines[e] = fsm.from_regex(e)
            out.append(machines[e].accepts(list(w)))
        return pd.Series(out, dtype=object)

    class Transitions:
        def eval(self, expression):
            from langpath.language import fsm

            if expression is not None:
                m = fsm.from_regex(expression)
                for q, s, p in sorted(m.edges):
                    yield q, s, p, q in m.starts, p in m.finals

    class Machine:
        def eval(self, rules):
            from langpath.language import rsm

            if rules is not None:
                m = rsm.from_grammar(rules)
                of = {q: b for b, (start, _) in m.boxes.items() for q in m._states(start)}
                for q, s, p, call in m.transitions():
                    yield of[q], q, s, p, call

    spark.udf.register("lp_accepts", accepts)
    spark.udtf.register("lp_transitions", udtf(Transitions, returnType="q int, symbol string, p int, from_start boolean, to_final boolean"))
    spark.udtf.register("lp_machine", udtf(Machine, returnType="box string, q int, symbol string, p int, is_call boolean"))
