"""The registered queries of this package: each applies one operator to its whole table."""

from __future__ import annotations

from huecount.llm import html, langid, minhash, mixing, packing, pipeline, quality, secrets, sharding, topk, warc
from huecount.llm.common import table

DOCUMENT_OPERATORS = {
    "op1_language_id": langid.op1_language_id,
    "op2_sharding": sharding.op2_sharding,
    "op3_mixing": mixing.op3_mixing,
    "op4_packing": packing.op4_packing,
    "op5_quality": quality.op5_quality,
    "op6_near_duplicates": minhash.op6_near_duplicates,
    "op10_secret_scan": secrets.op10_secret_scan,
}


def queries():
    def on(name, f):
        return lambda spark, sf_dir: f(table(spark, sf_dir, name))

    named = {k: on("documents", f) for k, f in DOCUMENT_OPERATORS.items()}
    named["op7_html"] = on("pages", html.op7_html)
    named["op8_warc"] = on("pages", warc.op8_warc)
    named["op9_top_k"] = on("embeddings", topk.op9_top_k)
    named["pipeline"] = pipeline.run
    return named


def oracle_sql():
    return {"op3_mixing": mixing.SQL, "op8_warc": warc.SQL, "op9_top_k": topk.SQL}
