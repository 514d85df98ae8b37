"""Queries of this subpackage, one for each operator, and the SQL for those that SQL can express."""

from __future__ import annotations

from . import curriculum, merkle
from .chaining import op3_chained_passages
from .compression_lid import op7_compression_lid
from .curriculum import op5_curriculum_mix
from .merkle import op9_merkle_fingerprints
from .nbsvm import op10_nbsvm_quality
from .outliers import op1_robust_outliers
from .pieces import op6_piece_nbest
from .rollup import op8_token_rollup
from .simhash import op2_simhash_components
from .toxicity import op4_toxicity_boosted

QUERIES = {
    f.__name__: f
    for f in (
        op1_robust_outliers,
        op2_simhash_components,
        op3_chained_passages,
        op4_toxicity_boosted,
        op5_curriculum_mix,
        op6_piece_nbest,
        op7_compression_lid,
        op8_token_rollup,
        op9_merkle_fingerprints,
        op10_nbsvm_quality,
    )
}
ORACLES: dict[str, str] = {"op5_curriculum_mix": curriculum.ORACLE, "op9_merkle_fingerprints": merkle.ORACLE}
