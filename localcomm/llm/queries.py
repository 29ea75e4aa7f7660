"""Queries of this folder's operators and, where SQL can say it, the SQL that must give the same rows."""

from __future__ import annotations

from localcomm.llm import audio, chunks, curves, licenses, packing, quality, shingles, templates, unigram, warc

QUERIES = {
    "op1_audio": audio.op1_audio,
    "op2_warc": warc.op2_warc,
    "op3_packing": packing.op3_packing,
    "op4_templates": templates.op4_templates,
    "op5_curves": curves.op5_curves,
    "op6_quality": quality.op6_quality,
    "op7_shingle_join": shingles.op7_shingle_join,
    "op8_licenses": licenses.op8_licenses,
    "op9_chunk_store": chunks.op9_chunk_store,
    "op10_unigram": unigram.op10_unigram,
}

ORACLES: dict[str, str] = {
    "op2_warc": warc.ORACLE,
    "op4_templates": templates.passages_oracle(),
    "op8_licenses": licenses.oracle(),
}
