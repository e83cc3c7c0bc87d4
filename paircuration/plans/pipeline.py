"""The four-stage curation plan over function pairs."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from paircuration.config import CurationConfig
from paircuration.operators import dedup, detector, extract, greedy, stage1, stage2
from paircuration.sources.scratch import discard, settle


@dataclass
class Curation:
    candidates: DataFrame
    filtered: DataFrame
    retained: DataFrame
    firsts: DataFrame
    deduped: DataFrame
    final: DataFrame

    def stages(self) -> list[tuple[str, DataFrame]]:
        return [("candidates", self.candidates), ("stage1", self.filtered), ("stage2", self.retained), ("exact", self.firsts), ("near", self.deduped), ("final", self.final)]


def near_edges(df: DataFrame, id_col: str, text, cfg, scope: str | None = None, unique=None) -> DataFrame:
    """(lo, hi, sim) of near-duplicate pairs by the configured verification, inside each value of `scope` if one is named.

    With `unique`, only the first row of each of its values takes part; no text is moved for that.  Buckets propose far
    more pairs than are similar: pairs that `dedup.bound` excludes are left out where buckets meet.
    """
    rows = df.select(id_col, text.alias("_text"), *([scope] if scope else []))
    if cfg.verify != "none" and cfg.family == "affine31":
        made = dedup.profiles(rows, id_col, F.col("_text"), cfg, scope)
        if unique is not None:
            made = made.join(dedup.exact(df, unique, [id_col]).select(id_col), id_col, "left_semi")
        tokens = rows.select(id_col, dedup.token_set(F.col("_text")).alias("tokens"))
        pairs = _candidates(made, id_col, cfg)
        return dedup.verify_grouped(pairs, dedup.signatures(rows, id_col, F.col("_text"), cfg) if cfg.verify == "signature" else tokens, id_col, cfg.verify, cfg.tau_lsh)
    if unique is not None:
        df = settle(dedup.exact(df, unique, [id_col]), "firsts")
    sets = df.select(id_col, dedup.token_set(text).alias("tokens"))
    sigs = dedup.signatures(df.select(id_col, text.alias("_text")), id_col, F.col("_text"), cfg)
    if scope:
        sigs = sigs.join(df.select(id_col, scope), id_col)
    pairs = dedup.candidates(dedup.index(sigs, id_col, cfg, scope), id_col)
    return dedup.verify(pairs, sigs if cfg.verify == "signature" else sets, id_col, cfg.verify, cfg.tau_lsh)


def set_candidates(sets: DataFrame, id_col: str, cfg, firsts: DataFrame) -> DataFrame:
    """The pairs (lo, hi) that `near_edges` verifies, from token sets that are there already, among the ids of `firsts`."""
    return _candidates(dedup.set_profiles(sets, id_col, cfg).join(firsts, id_col, "left_semi"), id_col, cfg)


def _candidates(made: DataFrame, id_col: str, cfg) -> DataFrame:
    """Pairs of the profiles' rows, settled; profiles and bands are deleted as soon as they are there."""
    met = dedup.bounded_index(settle(made, "profiles"), id_col)
    idx = settle(met, "bands")
    discard(met)  # what it reads: the profiles and the buckets' members
    pairs = settle(dedup.bounded_candidates(idx, idx, id_col, cfg), "pairs")
    discard(idx)
    return pairs


def near_dedup(df: DataFrame, id_col: str, text, cfg) -> DataFrame:
    """Rows that the ordered pass keeps; without verification the buckets themselves are resolved."""
    if cfg.verify == "none":
        sigs = dedup.signatures(df.select(id_col, text.alias("_text")), id_col, F.col("_text"), cfg)
        verdicts = greedy.resolve_buckets(dedup.index(sigs, id_col, cfg), id_col)
    else:
        verdicts = greedy.resolve(near_edges(df, id_col, text, cfg))
    gone = verdicts.filter("NOT kept").select(F.col("id").alias(id_col))
    return df.join(gone, id_col, "left_anti")


def run(pairs: DataFrame, cfg: CurationConfig = CurationConfig(), skip: frozenset[str] = frozenset()) -> Curation:
    """All stages in order; `skip` names stages to leave out (ablations): stage1, stage2, exact, near, detector."""
    filtered = pairs if "stage1" in skip else stage1.apply(pairs, cfg.stage1)
    scored = stage2.score(stage2.dimensions(filtered), cfg.stage2)
    retained = scored if "stage2" in skip else stage2.retain(scored, cfg.stage2)
    text = dedup.normalise(F.col("code"), F.col("language"))
    firsts = retained if "exact" in skip else dedup.exact(retained, text, ["pair_id"])
    firsts = settle(firsts, "firsts")  # read several times below, and too large an expression to fold further
    deduped = firsts if "near" in skip else near_dedup(firsts, "pair_id", text, cfg.dedup)
    final = deduped if "detector" in skip else detector.policy(detector.score(deduped, cfg.detector), cfg.detector)
    return Curation(pairs, filtered, retained, firsts, deduped, final)


def funnel(pairs: DataFrame, curation: Curation, cfg: CurationConfig = CurationConfig()) -> DataFrame:
    """Rows after each stage and the share of all candidates; the threshold and score stages are counted in one annotated pass."""
    judged = stage2.score(stage2.dimensions(stage1.apply(pairs, cfg.stage1, "annotate")), cfg.stage2)
    passing = F.size("failed") == 0
    counts = judged.agg(F.count(F.lit(1)).alias("candidates"), F.count_if(passing).alias("stage1"), F.count_if(passing & (F.col("quality") >= cfg.stage2.min_score)).alias("stage2"))
    rows = counts.selectExpr("stack(3, 0, 'candidates', candidates, 1, 'stage1', stage1, 2, 'stage2', stage2) as (step, stage, kept)")
    for i, (name, df) in enumerate(curation.stages()[3:]):
        rows = rows.union(df.agg(F.count(F.lit(1)).alias("kept")).select(F.lit(i + 3).alias("step"), F.lit(name).alias("stage"), "kept"))
    return rows.withColumn("retention", F.try_divide("kept", F.max("kept").over(Window.partitionBy(F.lit(1)))))  # six rows


def from_files(files: DataFrame, version: str, cfg: CurationConfig = CurationConfig(), licences: list[str] | None = None, max_idle_days: int | None = None,
               min_rows: int = 1, ts: str | None = None, before: str | None = None) -> Curation:
    """The whole plan: repository choice, temporal cutoff, extraction, the four stages; `split.stratified` deals the result.

    `files` has path, repo, language, source, licence, idle_days and url; repositories are judged by their files.  Files
    without a readable function give no rows.
    """
    chosen = extract.select_repos(files, min_rows=min_rows, licences=licences, max_idle_days=max_idle_days, doc="source")
    if ts is not None and before is not None:
        chosen = extract.temporal_cutoff(chosen, ts, before)
    found = extract.extract_functions(chosen)
    return run(settle(extract.pairs(found, chosen, version), "extracted"), cfg)
