"""The registered queries of this subpackage, and their SQL where there is one."""

from __future__ import annotations

from ._shared import table
from .decontaminate import op4_decontaminate
from .jaccard import op8_jaccard
from .language_id import op2_language
from .ogg_media import op1_ogg
from .packing import op5_packing
from .quality import op10_quality
from .spans import op6_spans
from .token_rollup import op3_rollup
from .toxicity import op9_toxicity
from .wrappers import op7_html


def _over(function, *names):
    return lambda spark, sf_dir: function(*(table(spark, sf_dir, n) for n in names))


def queries() -> dict:
    import corpus_pipeline

    return {
        "op1_ogg_media": _over(op1_ogg, "documents"),
        "op2_language_id": _over(op2_language, "documents"),
        "op3_token_rollup": _over(op3_rollup, "documents", "labels"),
        "op4_string_tiling": _over(op4_decontaminate, "documents", "benchmark"),
        "op5_best_fit_packing": _over(op5_packing, "documents"),
        "op6_sentence_spans": _over(op6_spans, "documents"),
        "op7_html_wrappers": _over(op7_html, "pages"),
        "op8_jaccard_join": _over(op8_jaccard, "documents"),
        "op9_toxicity": _over(op9_toxicity, "documents", "labels"),
        "op10_quality": _over(op10_quality, "documents", "labels"),
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict:
    """None: op3 counts with real vocabularies, the others have models, tilings or searches; all are held against brute force."""
    return {}
