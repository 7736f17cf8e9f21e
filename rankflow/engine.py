"""One object over programs, views, updates and SQL.

    engine = Engine(spark)
    engine.matrix("A", cells, 25, 25)                      # a frame (i, j, v)
    engine.view("p", "dynamic A(25, 25)  B = A @ A  out C = B @ B")
    engine.update("p", "A", changes)                       # a frame (i, j, v) of additions
    engine.sql("SELECT sum(v) FROM p_C")
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .functions import udfs
from .operators import backends, coo, models
from .plans import compile as comp
from .plans import cost, frontend
from .streaming import refresh
from .streaming.store import ViewStore


class Engine:
    """backend: coo (any size), block (dense panels, thin factors) or local (small matrices on the driver)."""

    def __init__(self, spark: SparkSession, backend: str = "coo", store: str | None = None):
        self.spark, self.backend = spark, backends.backend(spark, backend)
        self.store = ViewStore(spark, store) if store else None
        self.matrices: dict[str, coo.Coo] = {}
        self.views: dict[str, models.View] = {}
        udfs.register(spark)

    def matrix(self, name: str, cells: DataFrame, rows: int, cols: int) -> None:
        """Names a matrix; cells of one place are added, and null, infinite or outlying ones are an error."""
        self.matrices[name] = coo.clean(cells, rows, cols)

    def view(self, name: str, source: str, strategy: str = "auto", **how) -> models.View:
        """Loads a program's matrices and computes its views; ``auto`` takes the cheaper of re-evaluation and factored changes."""
        program = frontend.parse(source)
        view = models.View(self.backend, program, {n: self.matrices[n] for n in program.inputs}, strategy, **how)
        self.views[name] = view
        self._publish(name)
        return view

    def update(self, name: str, matrix: str, changes: DataFrame) -> models.RefreshReport:
        """Adds cell changes to an input and refreshes the view."""
        report = self.views[name].apply_batch(matrix, changes)
        self._publish(name)
        return report

    def stream(self, name: str, matrix: str, changes: DataFrame, checkpoint: str) -> None:
        """Applies a stream of cell changes as far as it goes; with a store, restarts go on where the last run ended."""
        refresh.run(changes, refresh.Refresher(self.views[name], matrix, self.store), checkpoint)
        self._publish(name)

    def frame(self, name: str, output: str | None = None) -> DataFrame:
        return self.views[name].frame(output)

    def sql(self, query: str) -> DataFrame:
        """Spark SQL over the outputs of views, named view_output, with the functions of ``functions.udfs``."""
        return self.spark.sql(query)

    def explain(self, name: str) -> str:
        """The triggers of a view, with the cost of each and of computing it anew."""
        view = self.views[name]
        ranks = dict.fromkeys(view.program.dynamic, 1)
        costs = cost.program_cost(view.program, ranks)
        triggers = comp.compile_program(view.program, ranks)
        lines = [f"strategy {view.strategy}; anew {cost.reevaluation_cost(view.program):.4g} operations"]
        return "\n".join(lines + [f"{t.explain()}\n  costs {costs[n]:.4g} operations" for n, t in triggers.items()])

    def _publish(self, name: str) -> None:
        for output in self.views[name].program.outputs:
            self.views[name].frame(output).createOrReplaceTempView(f"{name}_{output}")
