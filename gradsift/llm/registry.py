"""The queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from gradsift.llm.chat import OP10_SQL, op10_grammar_round_trip
from gradsift.llm.fingerprints import op9_invertible_sketch
from gradsift.llm.jaccard_join import op8_signature_tree_join
from gradsift.llm.packing import op1_best_two_fit
from gradsift.llm.quality import op4_robust_outliers
from gradsift.llm.sharding import op5_hilbert_shards
from gradsift.llm.suffix_dedup import op2_difference_cover
from gradsift.llm.token_rollup import op6_delta_rollup
from gradsift.llm.tokens import op3_bpe_round_trip
from gradsift.llm.warc import OP7_SQL, op7_boundary_chain

QUERIES = {
    "op1_best_two_fit": op1_best_two_fit,
    "op2_difference_cover": op2_difference_cover,
    "op3_bpe_round_trip": op3_bpe_round_trip,
    "op4_robust_outliers": op4_robust_outliers,
    "op5_hilbert_shards": op5_hilbert_shards,
    "op6_delta_rollup": op6_delta_rollup,
    "op7_boundary_chain": op7_boundary_chain,
    "op8_signature_tree_join": op8_signature_tree_join,
    "op9_invertible_sketch": op9_invertible_sketch,
    "op10_grammar_round_trip": op10_grammar_round_trip,
}
ORACLES: dict[str, str] = {"op7_boundary_chain": OP7_SQL, "op10_grammar_round_trip": OP10_SQL}
