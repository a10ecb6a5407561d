"""The queries of this folder and their SQL, by name."""

from __future__ import annotations

from . import ann, bm25, bpe, langid, licenses, mixing, secrets, simhash, toxicity, warc

QUERIES = {
    "op1_warc": warc.op1_warc,
    "op2_nearest": ann.op2_nearest,
    "op3_mixing": mixing.op3_mixing,
    "op4_simhash": simhash.op4_simhash,
    "op5_langid": langid.op5_langid,
    "op6_toxicity": toxicity.op6_toxicity,
    "op7_search": bm25.op7_search,
    "op8_secrets": secrets.op8_secrets,
    "op9_licenses": licenses.op9_licenses,
    "op10_bpe": bpe.op10_bpe,
}

ORACLES = {"op1_warc": warc.SQL, "op2_nearest": ann.SQL, "op3_mixing": mixing.SQL, "op8_secrets": secrets.SQL}
