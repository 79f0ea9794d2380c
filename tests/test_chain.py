"""Supersteps that share a job."""

from vertexalg.baselines.worklist import ResidualProgram, pagerank_residual
from vertexalg.algorithms.pagerank import with_out_degree
from vertexalg.engine import chainable, run_program
from vertexalg.graphs import derive


def test_residuals_settle(spark, sf):
    """Supersteps past the end change nothing, so ranks by residuals take up to three in a job, and end as they do one by one."""
    program = ResidualProgram(0.15, 1e-2)
    assert chainable(program)
    g = derive.graph(spark, sf, "trade")
    one, three = (run_program(with_out_degree(g), program, 200, chain=n) for n in (1, 3))
    assert [s[1:6] for s in one.steps] == [s[1:6] for s in three.steps] and one.converged and three.converged
    a, b = ({r.vid: round(r["rank"], 9) for r in out.state.collect()} for out in (one, three))
    assert a == b and len(a) == pagerank_residual(g, eps=1e-2).count()
