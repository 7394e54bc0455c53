"""The queries of the corpus operators, and their SQL where SQL can express them."""

from __future__ import annotations

from . import bpe, linededup, mixing, sharding, simhash, spotsigs, toxicity, urls, vectors, warc

QUERIES = {
    "op1_simhash": simhash.op1_simhash,
    "op2_sharding": sharding.op2_sharding,
    "op3_urls": urls.op3_urls,
    "op4_mixing": mixing.op4_mixing,
    "op5_linededup": linededup.op5_linededup,
    "op6_vectors": vectors.op6_vectors,
    "op7_warc": warc.op7_warc,
    "op8_bpe": bpe.op8_bpe,
    "op9_spotsigs": spotsigs.op9_spotsigs,
    "op10_toxicity": toxicity.op10_toxicity,
    "spotsigs_groups": spotsigs.spotsigs_groups,
}

ORACLES = {
    "op4_mixing": mixing.oracle(),
    "op5_linededup": linededup.oracle(),
    "op6_vectors": vectors.oracle(),
    "op7_warc": warc.oracle(),
}
