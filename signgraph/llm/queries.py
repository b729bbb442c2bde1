"""Registration of the ten operators and the pipeline."""
from __future__ import annotations

from . import lines, media, packing, pieces, quality, rules, simhash, suffix, toxicity, warc

QUERIES = {
    "op1_suffix_dedup": suffix.op1_suffix_dedup,
    "op2_simhash": simhash.op2_simhash,
    "op3_packing": packing.op3_packing,
    "op4_byte_cnn": quality.op4_byte_cnn,
    "op5_warc": warc.op5_warc,
    "op6_toxicity_mil": toxicity.op6_toxicity_mil,
    "op7_transport_stream": media.op7_transport_stream,
    "op8_robust_rules": rules.op8_robust_rules,
    "op9_line_dedup": lines.op9_line_dedup,
    "op10_sentencepiece": pieces.op10_sentencepiece,
}
ORACLES = {"op5_warc": warc.OP5_SQL}
