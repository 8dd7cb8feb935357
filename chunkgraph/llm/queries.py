"""The operators of this package as driver queries: name -> (spark, sf_dir) -> DataFrame, and SQL where SQL can say it."""

from __future__ import annotations

from . import bpe, decontaminate, embeddings, fmindex, langid, minhash, pii, quality, suffixarray, urls
from .common import table


def queries() -> dict:
    docs = lambda f: lambda spark, sf_dir: f(table(spark, sf_dir, "documents"))
    return {
        "op1_decontaminate": decontaminate.query,
        "op2_byte_bpe": docs(bpe.digests),
        "op3_personal_data": docs(pii.report),
        "op4_quality": quality.query,
        "op5_language": langid.query,
        "op6_url_filter": urls.query,
        "op7_substring_dedup": docs(fmindex.report),
        "op8_embedding_near_dedup": embeddings.query,
        "op9_minhash_near_dedup": minhash.query,
        "op10_suffix_array_dedup": docs(suffixarray.report),
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_decontaminate": decontaminate.ORACLE_SQL, "op8_embedding_near_dedup": embeddings.ORACLE_SQL}
