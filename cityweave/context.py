"""What queries over one folder share: the city, its links, the virtual graph and written graphs.

Links and graphs are written once for a folder and session, to the shared
scratch folder, and read by every query that needs them.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession

from cityweave.operators import linker
from cityweave.plans import graph, mappings, ontology
from cityweave.scratch import Scratch
from cityweave.session import broadcast_by_measure, plan_without_call_sites, ship
from cityweave.sources.city import City
from cityweave.workload import ByHand

_known: dict[tuple[str, int, str], Context] = {}


@dataclass
class Context:
    spark: SparkSession
    sf_dir: str

    @cached_property
    def scratch(self) -> Scratch:
        return Scratch(self.spark, "city")

    @cached_property
    def city(self) -> City:
        return City(self.spark, self.sf_dir)

    @cached_property
    def links(self) -> linker.LinkResult:
        return linker.run(self.city, scratch=self.scratch)

    @cached_property
    def ontology(self) -> ontology.Ontology:
        return ontology.vocabulary()

    @cached_property
    def store(self) -> mappings.Store:
        return mappings.Store(self.city, lambda: self.links, self.ontology)

    @cached_property
    def virtual(self) -> graph.VirtualGraph:
        return graph.VirtualGraph(self.ontology, mappings.catalogue(), self.store)

    @cached_property
    def naive(self) -> graph.VirtualGraph:
        return graph.VirtualGraph(self.ontology, mappings.catalogue(), self.store, optimize=False)

    @cached_property
    def by_hand(self) -> ByHand:
        return ByHand(self.city, lambda: self.links)

    @cached_property
    def triples(self) -> DataFrame:
        """All triples, as the layout by predicate has them: they are written once."""
        return self.materialized("predicate").table.drop("p_id")

    @cached_property
    def kept(self) -> dict[str, object]:
        """Further tables and graphs that several queries share."""
        return {}

    @cached_property
    def _written(self) -> dict[str, graph.MaterializedGraph]:
        return {}

    def all_triples(self) -> DataFrame:
        """All triples, as they were written if they were, else as they are made."""
        return self.triples if "predicate" in self._written else self.virtual.materialize()

    def materialized(self, layout: str) -> graph.MaterializedGraph:
        if layout not in self._written:
            self._written[layout] = graph.MaterializedGraph.write(self.all_triples(), self.ontology, layout, f"{self.scratch.base}/graph-{layout}")
        return self._written[layout]

    def asked(self, layout: str) -> graph.MaterializedGraph:
        """The written graph for queries: as a whole if it was written so, else with the parts that they ask for."""
        if layout in self._written:
            return self._written[layout]
        if (key := f"{layout} in parts") not in self.kept:
            self.kept[key] = graph.GraphInParts(self.spark, self.ontology, layout, f"{self.scratch.base}/parts-{layout}", virtual=self.virtual)
        return self.kept[key]


def context(spark: SparkSession, sf_dir: str) -> Context:
    ship(spark)
    broadcast_by_measure(spark)
    plan_without_call_sites(spark)
    key = (spark.sparkContext.applicationId, id(spark), sf_dir)
    if key not in _known:
        _known[key] = Context(spark, sf_dir)
    return _known[key]
