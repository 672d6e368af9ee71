"""Declared schemas of the engine's tables."""

from __future__ import annotations

#: One row per sample and id: bags are several rows of one (sample, feature).
SAMPLES = "sample_id bigint, day int, label int, feature string, id bigint"
#: Latent values and use counts of every id of a feature's vocabulary.
TEACHER = "feature string, id bigint, vec array<double>, accesses bigint"
#: Clusters on one latent dimension, in the order of value; pos counts from 1.
CHAIN = "feature string, dim int, pos bigint, value double, size bigint, accesses bigint"
#: Final clusters as intervals of chain positions.
CUTS = "feature string, dim int, row bigint, lo_pos bigint, hi_pos bigint, value double, size bigint, accesses bigint"
#: The learned lookup: id -> row, once per slot.
FOLD_MAP = "feature string, slot int, id bigint, row bigint"
#: What one round of agglomeration did.
TRACE = "feature string, dim int, round int, n bigint, r bigint, links bigint, kept1 bigint, kept2 bigint, fallback boolean, selected bigint, runs_split bigint, merges bigint"
