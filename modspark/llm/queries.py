"""The queries of the corpus operators and their SQL."""

from __future__ import annotations

from . import bpe, fingerprints, jaccard, line_templates, mixing, pii, planes, quality, secrets, tiff

QUERIES = {
    "op1_secret_ownership": secrets.op1_secret_ownership,
    "op2_adaptive_jaccard": jaccard.op2_adaptive_jaccard,
    "op3_piecewise_fingerprints": fingerprints.op3_piecewise_fingerprints,
    "op4_tiff_pages": tiff.op4_tiff_pages,
    "op5_pivotal_mix": mixing.op5_pivotal_mix,
    "op6_semi_markov_pii": pii.op6_semi_markov_pii,
    "op7_transducer_bpe": bpe.op7_transducer_bpe,
    "op8_line_templates": line_templates.op8_line_templates,
    "op9_nb_svm_quality": quality.op9_nb_svm_quality,
    "op10_plane_shards": planes.op10_plane_shards,
}

ORACLES: dict[str, str] = {
    "op2_adaptive_jaccard": jaccard.OP2_SQL,
    "op8_line_templates": line_templates.OP8_SQL,
}
