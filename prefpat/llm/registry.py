"""The queries of this subpackage by name, and the SQL of those that SQL can express."""

from prefpat.llm import bpe, langid, linededup, ngram, packing, quality, sharding, simhash, urlfilter, webp

QUERIES = {
    "op1_bpe": bpe.op1_bpe,
    "op2_urlfilter": urlfilter.op2_urlfilter,
    "op3_simhash": simhash.op3_simhash,
    "op4_ngram": ngram.op4_ngram,
    "op5_langid": langid.op5_langid,
    "op6_webp": webp.op6_webp,
    "op7_quality": quality.op7_quality,
    "op8_sharding": sharding.op8_sharding,
    "op9_packing": packing.op9_packing,
    "op10_line_dedup": linededup.op10_line_dedup,
}

ORACLES = {
    "op2_urlfilter": urlfilter.OP2_SQL,
    "op4_ngram": ngram.OP4_SQL,
    "op7_quality": quality.OP7_SQL,
    "op8_sharding": sharding.OP8_SQL,
    "op10_line_dedup": linededup.OP10_SQL,
}
