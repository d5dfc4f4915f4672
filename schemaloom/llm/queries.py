"""The corpus operators' queries and DuckDB oracles."""

from schemaloom.llm import bpe, fmindex, lines, planes, quality, simhash, sketch, spans, suffixes, warc

QUERIES = {
    "op1_sentence_spans": spans.op1_sentence_spans,
    "op2_neighbour_quality": quality.op2_neighbour_quality,
    "op3_warc_normaliser": warc.op3_warc_normaliser,
    "op4_token_planes": planes.op4_token_planes,
    "op5_maximal_repeats": suffixes.op5_maximal_repeats,
    "op6_simhash_tries": simhash.op6_simhash_tries,
    "op7_streaming_bpe": bpe.op7_streaming_bpe,
    "op8_line_dedup": lines.op8_line_dedup,
    "op9_fm_decontamination": fmindex.op9_fm_decontamination,
    "op10_scaled_sketch": sketch.op10_scaled_sketch,
}
ORACLES = {"op1_sentence_spans": spans.OP1_SQL, "op3_warc_normaliser": warc.OP3_SQL, "op8_line_dedup": lines.OP8_SQL, "op9_fm_decontamination": fmindex.OP9_SQL}
