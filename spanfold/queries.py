"""All registered queries of the range-model engine, and the flagship."""

from __future__ import annotations

from spanfold.registry import planning, relational, state  # noqa: F401  (registers)
from spanfold.registry.base import REGISTRY


def queries() -> dict:
    return {name: f for name, (f, _) in REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in REGISTRY.items() if sql}


def flagship(spark, sf_dir):
    """Plan and run one linear-regression request over kept models: its segments and weights."""
    from spanfold import workloads as W
    from spanfold.engine import Engine
    from spanfold.registry.base import ends_of
    from spanfold.registry.state import size_of
    from spanfold.plans.ranges import Range
    from spanfold.sources.layout import lineitem_source
    from spanfold.sources.points import LINREG

    source = lineitem_source(spark, sf_dir)
    e = ends_of(size_of(source))
    engine = Engine(spark)
    W.keep_exact(engine, source, LINREG, [Range(e["a"], e["c"]), Range(e["a"], e["b"]), Range(e["b"], e["d"]), Range(e["d"], e["f"])])
    answer = engine.fit(source, LINREG, e["c"], e["e"])
    rows = [("segment", f"{s.sign:+d} {s.kind} {s.model_id or ''}".strip(), s.lo, s.hi, float(s.cost)) for s in answer.plan.segments]
    rows += [("weight", c.name, None, None, float(v)) for c, v in zip(LINREG.columns(), answer.weights(ridge=1.0))]
    return spark.createDataFrame(rows, "part string, name string, lo long, hi long, value double")
