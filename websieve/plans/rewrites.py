"""The planner's own choices, as functions of sizes and options; Catalyst does the rest."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import dedup
from .pipeline import CurateOptions


@dataclass(frozen=True)
class Stage:
    name: str
    needs_text: bool
    per_language: bool = False


STAGES = (Stage("split", True), Stage("key", True), Stage("dedup", False), Stage("identify", True), Stage("tokenize", True, True), Stage("score", False, True), Stage("bucket", False, True), Stage("sink", True))


def optimize(opts: CurateOptions, has_model: bool = True) -> list[str]:
    """The order in which stages run. Text is left out of key shuffles (it meets positions again after dedup), documents are
    discarded before anything costly, and stages of the language model are skipped where there is no model."""
    names = [s.name for s in STAGES]
    if opts.scope is None:
        names = [n for n in names if n not in ("key", "dedup")]
    if opts.order == "lid_first":
        names.remove("identify")
        names.insert(0, "identify")
    if not has_model or not opts.lm_order:
        names = [n for n in names if n not in ("tokenize", "score", "bucket")]
    return names


def index_by_broadcast(unique_keys: int, bytes_per_key: float = 26.7, limit: int = 256 << 20) -> bool:
    """Whether an index of so many keys is small enough to send to every executor."""
    return unique_keys * bytes_per_key <= limit


def lookup(keys: DataFrame, index: DataFrame) -> DataFrame:
    """Set lookup with the join chosen by the size of the index."""
    side = index.select("h64").distinct()
    if index_by_broadcast(side.count()):
        side = F.broadcast(side)
    return keys.join(side, "h64", "left_anti")
