"""The whole method: log, seeds, knowledge base and corpus to ranked facets."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.operators import candidates, cluster, group, propagate, retrieve, select, similarity
from facetspark.sources import worlds
from facetspark.sources.storage import cut


@dataclass(frozen=True)
class Params:
    k: float = 0.1
    mode: str = "indicator"
    cap: int = 30
    m: int = 8
    n: int = 8
    sigma: float = 0.35
    method: str = "best_match"
    fields: tuple[str, ...] = ("head", "snippet")
    strip_seed: bool = True
    sources: tuple[str, ...] = ("refine", "super")
    ambiguity: str = "drop"
    grouping: bool = True
    dedupe: bool = True


def capped(scored: DataFrame, n: int) -> DataFrame:
    """The best ``n`` facets per seed; ties by text."""
    order = F.row_number().over(W.partitionBy("query").orderBy(F.round("score", 9).desc(), "facet"))
    return scored.withColumn("rank", order).where(F.col("rank") <= n).drop("rank")


#: parameters that each stage depends on, besides those of the stages before it
DEPENDS = {
    "lines": (),
    "log": (),
    "instance": ("sources",),
    "scored": ("sources", "k", "mode"),
    "pool": ("sources", "k", "mode", "cap"),
    "index": ("fields",),
    "hits": ("sources", "k", "mode", "cap", "fields", "m"),
    "vectors": ("sources", "k", "mode", "cap", "fields", "m", "strip_seed"),
    "sim": ("sources", "k", "mode", "cap", "fields", "m", "strip_seed", "method"),
}
_stages: dict[tuple, object] = {}


@dataclass
class Commerce:
    """Every stage over the commerce world.

    Stages that several later ones read are written once, so plans stay short, and shared by
    runs whose parameters agree up to them.
    """

    t: worlds.Tables
    p: Params = field(default_factory=Params)

    def _shared(self, stage: str, make):
        key = (self.t.spark.sparkContext.applicationId, self.t.folder, stage, *(getattr(self.p, n) for n in DEPENDS[stage]))
        if key not in _stages:
            made = make()
            _stages[key] = cut(made, stage) if isinstance(made, DataFrame) else made
        return _stages[key]

    @cached_property
    def lines(self) -> DataFrame:
        return self._shared("lines", lambda: worlds.commerce_lines(self.t))

    @cached_property
    def log(self) -> DataFrame:
        return self._shared("log", lambda: worlds.commerce_log(self.t, self.lines))

    @cached_property
    def corpus(self) -> DataFrame:
        return worlds.corpus(self.t, self.lines)

    @cached_property
    def seeds(self) -> DataFrame:
        return worlds.seeds(self.t)

    @cached_property
    def nodes(self) -> DataFrame:
        return propagate.classes_of(self.seeds, worlds.membership(self.t))

    @cached_property
    def instance(self) -> DataFrame:
        return self._shared("instance", lambda: candidates.keyed(candidates.mine(self.log, self.seeds, self.p.sources), self.seeds))

    @cached_property
    def scored(self) -> DataFrame:
        return self._shared("scored", lambda: propagate.propagate(self.instance, self.nodes, self.p.k, self.p.mode))

    @cached_property
    def pool(self) -> DataFrame:
        """The capped facets of every seed, with the text that poses them."""
        return self._shared("pool", lambda: candidates.posed(capped(self.scored, self.p.cap), self.seeds))

    @cached_property
    def index(self) -> retrieve.Index:
        return self._shared("index", lambda: retrieve.build_index(self.corpus, self.p.fields))

    @cached_property
    def hits(self) -> DataFrame:
        return self._shared("hits", lambda: retrieve.facet_hits(self.pool, self.index, self.p.m))

    @cached_property
    def vectors(self) -> DataFrame:
        return self._shared("vectors", lambda: similarity.doc_vectors(self.hits, self.index, self.p.strip_seed))

    @cached_property
    def sim(self) -> DataFrame:
        return self._shared("sim", lambda: (similarity.word_sim(self.pool) if self.p.method == "words" else similarity.facet_sim(self.hits, self.vectors, self.p.method)))

    @cached_property
    def clusters(self) -> DataFrame:
        edges = cluster.threshold_edges(self.sim, self.p.sigma if self.p.dedupe else float("inf"))
        return cut(cluster.label_clusters(cluster.components(self.pool.select("query", "facet"), edges), self.pool), "clusters")

    @cached_property
    def groups(self) -> DataFrame:
        labels = self.clusters.where("is_label")
        matches = group.match_entities(labels, worlds.membership(self.t), worlds.aliases(self.t), worlds.ambiguous(self.t), self.p.ambiguity)
        return cut(group.by_category(labels, matches if self.p.grouping else matches.where("false")), "groups")

    @cached_property
    def ranked(self) -> DataFrame:
        return select.greedy(self.groups, self.sim, self.p.n)
