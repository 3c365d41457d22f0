"""Queries of the operators over the given tables, and the SQL of those that SQL can express on whole tables."""

from __future__ import annotations

from .audio import op2_audio_features
from .count_fst import op6_token_counts
from .embeddings import op5_pca_tiles
from .language_id import op9_hyperdimensional
from .minhash import op4_super_minhash
from .packing import op10_concatenate_and_cut
from .pseudo_likelihood import op7_pseudo_likelihood
from .quality import op1_positive_unlabelled
from .token_files import op3_token_files
from .trie_codec import op8_prefix_trie

QUERIES = {
    f.__name__: f
    for f in (
        op1_positive_unlabelled, op2_audio_features, op3_token_files, op4_super_minhash, op5_pca_tiles,
        op6_token_counts, op7_pseudo_likelihood, op8_prefix_trie, op9_hyperdimensional, op10_concatenate_and_cut,
    )
}
#: Tokenizers, learned models, sampled signatures and coded files are beyond SQL; what SQL can say of documents as
#: sets is an all-pairs join, too slow on whole tables. Each query is tested against a brute-force version instead.
ORACLES: dict[str, str] = {}
