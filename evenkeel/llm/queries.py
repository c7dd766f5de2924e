"""The ten operators over their whole tables, and their SQL where SQL can say it."""

from __future__ import annotations

from evenkeel.llm import audio, bpe, embedding_dedup, mixing, pii, secrets, simhash, toxicity, urlfilter, warc


def queries() -> dict:
    return {
        "op1_warc": warc.op1_warc,
        "op2_bpe": bpe.op2_bpe,
        "op3_url_filter": urlfilter.op3_url_filter,
        "op4_secrets": secrets.op4_secrets,
        "op5_embedding_dedup": embedding_dedup.op5_embedding_dedup,
        "op6_pii": pii.op6_pii,
        "op7_audio": audio.op7_audio,
        "op8_mixing": mixing.op8_mixing,
        "op9_toxicity": toxicity.op9_toxicity,
        "op10_simhash": simhash.op10_simhash,
    }


def oracle_sql() -> dict[str, str]:
    return {"op8_mixing": mixing.OP8_SQL}
