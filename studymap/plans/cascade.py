"""The cascade: layers in order, the first that decides a study ends its way; dear layers see only what cheap ones left.

A layer is (number, function of the studies still open -> (study_id, label)). Reordering the list gives every ablation.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..operators import layers, network, rules, votes


class Corpus:
    """The tables that a cascade reads, by name; a part given as a function is made when it is first asked for, once.

    study, series, class_ref, code_ref, desc_ref, keyword_ref, rule_ref (or None), keys (tags that vote), and what the networks say: either network_scores
    (study_id, series_no, label, confidence_u), or logits (study_id, series_no, network, logits) with route_ref (modality, network, votes), temperatures
    (network, temperature) and net_classes (class_id, label).
    """

    def __init__(self, **parts):
        self._parts = {"rule_ref": None, "keys": ("brand", "flag", "name", "pack"), "logits": None} | parts

    def __getattr__(self, name):
        parts = self.__dict__.get("_parts", {})
        if name not in parts:
            raise AttributeError(name)
        if callable(parts[name]):
            parts[name] = parts[name]()
        return parts[name]

    def but(self, **other) -> Corpus:
        return Corpus(**(self._parts | other))


@dataclass(frozen=True)
class Config:
    order: tuple = (1, 2, 3, 4, 5)
    tier: str = "full"
    majority: str = "plurality"
    short_match: str = "word"
    tie: str = "abstain"
    extra: dict = field(default_factory=dict)


def meta_ballot(c: Corpus, open_: DataFrame | None, cfg: Config) -> DataFrame:
    series = c.series if open_ is None else c.series.join(open_.select("study_id"), "study_id", "left_semi")
    v = votes.metadata_votes(series, c.keyword_ref, c.keys, short_match=cfg.short_match)
    return _ruled(c, v, series, cfg)


def net_ballot(c: Corpus, open_: DataFrame | None, cfg: Config) -> DataFrame:
    """Votes of the networks on the series of the studies still open: given scores, or logits routed by modality and tempered."""
    if c.logits is None:
        return network.votes(c.network_scores if open_ is None else c.network_scores.join(open_.select("study_id"), "study_id", "left_semi"))
    series = c.series if open_ is None else c.series.join(open_.select("study_id"), "study_id", "left_semi")
    routed = network.route(series.select("study_id", "series_no", "modality"), c.route_ref)
    return network.votes_from_logits(routed.join(c.logits, ["study_id", "series_no", "network"]), c.net_classes, c.temperatures)


def _ruled(c: Corpus, v: DataFrame, series: DataFrame, cfg: Config) -> DataFrame:
    if c.rule_ref is None:
        return v
    v = v.join(series.select("study_id", "series_no", "modality"), ["study_id", "series_no"])
    return rules.apply(v.select("study_id", "label", "weight_u", "origin", "series_no", "modality"), c.rule_ref, cfg.tier).drop("modality")


def layer_functions(c: Corpus, cfg: Config) -> dict[int, Callable[[DataFrame], DataFrame]]:
    return {
        1: lambda s: layers.match_code(s, c.code_ref),
        2: lambda s: layers.match_description(s, c.desc_ref),
        3: lambda s: layers.match_partial(s, c.keyword_ref, short_match=cfg.short_match, tie=cfg.tie),
        4: lambda s: votes.decide(meta_ballot(c, s, cfg), cfg.majority),
        5: lambda s: votes.decide(net_ballot(c, s, cfg), cfg.majority),
    } | cfg.extra


def classify(c: Corpus, cfg: Config = Config()) -> DataFrame:
    """(study_id, label, layer) of the studies that some layer decides. Neighbouring exact layers are one pass; what a dearer layer decides is written down before the next reads the rest."""
    functions = layer_functions(c, cfg)
    open_ = c.study.select("study_id", "procedure_code", "description")
    decided, order = None, list(cfg.order)

    def gained(got):
        return got if decided is None else decided.unionByName(got)

    while order:
        exact = []
        while order and order[0] in (1, 2) and order[0] not in cfg.extra:
            exact.append(order.pop(0))
        if len(exact) > 1:
            state = cut(layers.match_exact(open_, c.code_ref, c.desc_ref, exact))
            decided = gained(state.where("label is not null").select("study_id", "label", "layer"))
            open_ = state.where("label is null").drop("label", "layer")
            continue
        n = exact[0] if exact else order.pop(0)
        got = cut(functions[n](open_).select("study_id", "label", F.lit(n).alias("layer")))
        decided = gained(got)
        if order:
            open_ = open_.join(got, "study_id", "left_anti")
    return decided


def review_queue(study: DataFrame, ballot: DataFrame, decided: DataFrame, margin_u: int) -> DataFrame:
    """Studies for a person: unanswered ones, and those whose winner leads by less than margin_u."""
    ranked = ballot.groupBy("study_id").agg(F.sort_array(F.collect_list("weight_u"), asc=False).alias("w"))
    lead = ranked.select("study_id", (F.get("w", F.lit(0)) - F.coalesce(F.get("w", F.lit(1)), F.lit(0))).alias("lead"))
    x = study.select("study_id").join(decided.select("study_id", "label"), "study_id", "left").join(lead, "study_id", "left")
    return x.where(F.col("label").isNull() | (F.col("lead") < margin_u)).select("study_id", "label", "lead")
