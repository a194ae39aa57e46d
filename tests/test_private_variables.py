"""Variables of one atom alone are chosen within it, so joins of atoms don't multiply rows."""

from concord.model import Entangled, Var, atom, frame
from concord.operators.scc import scc_coordinate


def test_eight_atoms_of_one_value_are_no_product(spark):
    """Eight queries that share a value with 300 rows: 300 ** 8 rows if all combinations were joined."""
    qs = [Entangled(i).offer(atom("seat", i, Var("x"), Var("v"))).given(*[atom("seat", i + 1, Var("y"), Var("v"))] if i < 7 else []).where(atom("d", Var("x"), Var("v"))) for i in range(8)]
    data = spark.range(300).selectExpr("id + 3 AS a", "'one' AS v")
    run = scc_coordinate(frame(spark, qs), {"d": data})
    assert {r["n"] for r in run.nodes.where("status = 'ok'").collect()} == set(range(1, 9))
