"""The corpus operators' queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession

from .decontamination import op3_template_leaks
from .fingerprints import op8_threshold_sketches
from .html_extraction import op6_wrapper_extraction
from .licenses import op10_license_digests
from .near_dedup import op1_circulant_near_duplicates
from .oracles import SQL
from .pieces import op2_lattice_sampled_pieces
from .quality import op4_latent_neighbour_quality
from .sharding import op9_proportional_shards
from .suffix_dedup import op7_difference_cover_repeats
from .token_counts import op5_transducer_token_counts

OPERATORS = (
    op1_circulant_near_duplicates,
    op2_lattice_sampled_pieces,
    op3_template_leaks,
    op4_latent_neighbour_quality,
    op5_transducer_token_counts,
    op6_wrapper_extraction,
    op7_difference_cover_repeats,
    op8_threshold_sketches,
    op9_proportional_shards,
    op10_license_digests,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in OPERATORS} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    """What SQL can express; tests/llm holds the others against a brute-force version, a library or held-out labels."""
    return dict(SQL)
