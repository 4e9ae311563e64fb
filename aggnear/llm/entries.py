"""Queries and SQL of the corpus operators."""

from . import capfilters, chaining, idstore, langid, mixing, packing, quality, simhash, topk, urls


def pipeline(spark, sf_dir: str):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {"pipeline": pipeline, "op5_chaining": chaining.op5_chaining, "op1_idstore": idstore.op1_idstore, "op2_packing": packing.op2_packing, "op7_langid": langid.op7_langid, "op9_quality": quality.op9_quality, "op10_simhash": simhash.op10_simhash, "op3_caps": capfilters.op3_caps, "op4_urls": urls.op4_urls, "op6_mix": mixing.op6_mix, "op8_topk": topk.op8_topk}
ORACLES = {"op3_caps": capfilters.SQL, "op4_urls": urls.SQL, "op6_mix": mixing.SQL, "op8_topk": topk.SQL}
