"""Lossless rewrites of a near-duplicate plan, made before Catalyst sees it, and checks of physical plans."""

from __future__ import annotations

import contextlib
import io
import re
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.config import DedupConfig
from neardup.functions.text import grams_of
from neardup.operators import candidates, exact, verify
from neardup.operators.banding import bands as bands_of
from neardup.session import materialize


@dataclass(frozen=True)
class DedupPlan:
    """Logical steps of finding pairs above a threshold."""

    cfg: DedupConfig
    collapse: bool = False
    size_filter: bool = False
    distinct_first: bool = False
    hashed: bool = False
    expand: bool = True


def collapse_copies(p: DedupPlan) -> DedupPlan:
    """Copies of a text share every band: one of them goes through, and their pairs are added at the end."""
    return replace(p, collapse=True)


def filter_sizes(p: DedupPlan) -> DedupPlan:
    """Similarity is at most the ratio of set sizes, which the join on bands can test before sets move."""
    return replace(p, size_filter=True)


def distinct_before_verify(p: DedupPlan) -> DedupPlan:
    return replace(p, distinct_first=True)


def hash_grams(p: DedupPlan) -> DedupPlan:
    """Sets of 64-bit hashes stand for sets of strings in the exact check."""
    return replace(p, hashed=True)


RULES = (collapse_copies, filter_sizes, distinct_before_verify, hash_grams)


def optimise(p: DedupPlan) -> DedupPlan:
    for rule in RULES:
        p = rule(p)
    return p


def execute(p: DedupPlan, df: DataFrame) -> DataFrame:
    """(a, b, jaccard) of all documents."""
    docs = exact.representatives(df) if p.collapse else df
    bands = materialize(bands_of(docs, p.cfg), "bands")
    grams = grams_of(docs, p.cfg, hashed=p.hashed)
    if p.size_filter:
        sizes = grams.select("doc_id", F.size("grams").alias("n_grams"))
        pairs = candidates.size_filtered(bands, sizes, p.cfg.threshold)
    else:
        pairs = candidates.banded(bands)
    found = verify.verified(pairs, grams, p.cfg.threshold)
    if not p.distinct_first:
        found = found.distinct()
    if not p.collapse or not p.expand:
        return found
    real = grams_of(df, p.cfg, hashed=True).where(F.size("grams") > 0).select("doc_id")
    return exact.expand(found, exact.exact_groups(df).join(real, "doc_id", "left_semi"))


def plan_text(df: DataFrame) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def operators_of(df: DataFrame) -> dict[str, int]:
    """How often each physical operator stands in the plan."""
    head = plan_text(df).split("\n\n\n")[0]
    found: dict[str, int] = {}
    for name in re.findall(r"[*+\-: ]*([A-Z]\w+)(?: \(\d+\)| \()", head):
        found[name] = found.get(name, 0) + 1
    return found
