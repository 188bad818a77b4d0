"""Six sorted copies of the triples, one for each order of their positions, and a table by predicate."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.operators import shuffle_baseline
from probejoin.plans.patterns import TriplePattern
from probejoin.sources.storage import written

ORDERS = ("spo", "sop", "pso", "pos", "osp", "ops")
#: The copy whose leading positions are those given, for each shape.
COPY = {"spo": "spo", "sp?": "spo", "s?o": "sop", "s??": "spo", "?po": "pos", "?p?": "pso", "??o": "osp", "???": "spo"}


@dataclass
class SextupleStore:
    """Copies are written when they are first asked for."""

    triples: DataFrame
    held: dict[str, DataFrame] = field(default_factory=dict)

    def copy(self, name: str) -> DataFrame:
        """Range-partitioned and sorted by its order, so that what is given leads to few row groups."""
        if name not in self.held:
            self.held[name] = written(self.triples.select(*name).repartitionByRange(*name).sortWithinPartitions(*name), f"copy-{name}")
        return self.held[name]


def build(triples: DataFrame) -> SextupleStore:
    return SextupleStore(triples)


def read(store: SextupleStore, p: TriplePattern) -> DataFrame:
    return shuffle_baseline.scan(store.copy(COPY[p.shape()]), p)


def storage(store: SextupleStore, replication: int = 3) -> DataFrame:
    """Rows (layout, copies, stored_copies, n_rows): six orders against two indexes."""
    n = store.copy("spo").agg(F.count("*").alias("n"))
    layout = lambda name, k: n.select(F.lit(name).alias("layout"), F.lit(k).alias("copies"), F.lit(k * replication).alias("stored_copies"), (F.col("n") * k).alias("n_rows"))
    return layout("six orders", 6).unionByName(layout("two indexes", 2))


def predicate_balance(triples: DataFrame) -> DataFrame:
    """Rows (p, n): the row sizes of a table keyed by predicate."""
    return triples.groupBy("p").agg(F.count("*").alias("n"))
