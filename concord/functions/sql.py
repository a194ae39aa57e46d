"""SQL surface: a table function that parses the text form, and views over graphs and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from concord.model import parse_entangled

ATOMS = "role string, pos int, rel string, terms array<struct<var:string,const:string>>"


class _ParseEntangled:
    def eval(self, text: str):
        if text is None:
            return
        q = parse_entangled(text, 0)
        for role, atoms in (("post", q.post), ("head", q.head), ("body", q.body)):
            for pos, (rel, terms) in enumerate(atoms):
                yield role, pos, rel, [{"var": v, "const": c} for v, c in terms]


def register(spark: SparkSession) -> None:
    """``SELECT * FROM parse_eq('seat(1,x) from flights(x)')``; null gives no row, ill-formed text fails."""
    spark.udtf.register("parse_eq", udtf(_ParseEntangled, returnType=ATOMS))


def publish(eqs: DataFrame, ext: DataFrame, run=None, prefix: str = "eq") -> list[str]:
    """Temporary views <prefix>_queries, _edges, _safety and, of a run, _sets and _assignment."""
    from concord.operators.unify import safety

    views = {"queries": eqs, "edges": ext, "safety": safety(ext, eqs)}
    if run is not None:
        views |= {"sets": run.sets(), "assignment": run.assignment()}
    for name, df in views.items():
        df.createOrReplaceTempView(f"{prefix}_{name}")
    return [f"{prefix}_{name}" for name in views]
