"""A facade over graphs and stores that also gives them to SQL, as views.

``Engine(spark).graph("cobuy", sf_dir).store(reps=2)`` registers ``edges_cobuy``, ``adj_cobuy``,
``visits_cobuy`` and ``segments_cobuy``, so that an estimate is an aggregate in SQL. Closed forms
and ``segment_steps`` are SQL functions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from incwalk.functions import tables, theory
from incwalk.plans import graph as G
from incwalk.plans import personal
from incwalk.plans.update import WalkStore
from incwalk.plans.walks import Spec, segments
from incwalk.sources.coin_edges import CoinEdges
from incwalk.sources.graphs import GRAPHS, edges
from incwalk.store import save


class Engine:
    def __init__(self, spark: SparkSession):
        self.spark = spark
        theory.register(spark)
        tables.register(spark)
        spark.dataSource.register(CoinEdges)

    def graph(self, name: str, sf_dir: str) -> Graph:
        """One of the named graphs."""
        if name not in GRAPHS:
            raise ValueError(f"no graph of that name; there are {', '.join(GRAPHS)}")
        return self.edges(name, edges(self.spark, sf_dir, name))

    def edges(self, name: str, rows: DataFrame) -> Graph:
        """A graph of one's own: ``src, dst, ord``."""
        if not name.isidentifier():
            raise ValueError("a name of letters, digits and underscores is needed")
        return Graph(self, name, save(rows.select("src", "dst", "ord"), f"edges-{name}"))


class Graph:
    def __init__(self, engine: Engine, name: str, rows: DataFrame):
        self.engine, self.name, self.rows = engine, name, rows
        rows.createOrReplaceTempView(f"edges_{name}")
        G.slots(rows).createOrReplaceTempView(f"adj_{name}")

    def store(self, reps: int = 2, eps: float = 0.2, name: str | None = None, **spec) -> Store:
        """A maintained store of walks; ``spec`` are further fields of ``Spec``."""
        return Store(self.engine, name or self.name, WalkStore.create(self.rows, Spec(reps=reps, eps=eps, **spec)))


class Store:
    def __init__(self, engine: Engine, name: str, held: WalkStore):
        if not name.isidentifier():
            raise ValueError("a name of letters, digits and underscores is needed")
        self.engine, self.name, self.held = engine, name, held
        self._register()

    def _register(self) -> None:
        """Views of the store as it is now; views made before a batch keep showing the store before it."""
        self.held.visits().createOrReplaceTempView(f"visits_{self.name}")
        self.held.edges().createOrReplaceTempView(f"edges_{self.name}")
        segments(self.held.visits()).createOrReplaceTempView(f"segments_{self.name}")

    def pagerank(self) -> DataFrame:
        """``(node, visits, score)`` for forward walks; ``(node, hub, auth)`` for alternating ones."""
        spec, spark = self.held.spec, self.engine.spark
        if spec.alternating:
            return spark.sql(f"SELECT node, count_if(role = 'hub') * {spec.eps}D / (n * {spec.reps}) AS hub, count_if(role = 'auth') * {spec.eps}D / ({1 - spec.eps}D * n * {spec.reps}) AS auth FROM visits_{self.name}, (SELECT count(DISTINCT src) AS n FROM visits_{self.name}) WHERE rep < {spec.reps} GROUP BY node, n")
        return spark.sql(f"SELECT node, count(*) AS visits, count(*) * {spec.eps}D / (n * {spec.reps}) AS score FROM visits_{self.name}, (SELECT count(DISTINCT src) AS n FROM visits_{self.name}) GROUP BY node, n")

    def update(self, changes: DataFrame, **how) -> DataFrame:
        """Applies ``op, src, dst, ord``, renews the views and gives the ledger."""
        ledger = self.held.apply(changes, **how)
        self._register()
        return ledger

    def topk(self, seeds: DataFrame, k: int = 10, **how) -> DataFrame:
        """The ``k`` nodes that a stitched walk from each seed visits most."""
        return personal.topk_personalised(self.held.visits(), self.held.edges(), seeds, k, self.held.spec, **how)
