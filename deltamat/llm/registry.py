"""The ten operators' queries, and SQL for those that SQL can express."""

from __future__ import annotations

from deltamat.llm import ann, chat, decontaminate, langid, lines, pieces, quality, secrets, simhash, warc

QUERIES = {
    f.__name__: f
    for f in (
        ann.op1_nearest,
        langid.op2_language_id,
        lines.op3_line_dedup,
        simhash.op4_simhash,
        pieces.op5_sentencepiece,
        quality.op6_quality,
        decontaminate.op7_decontamination,
        chat.op8_chat,
        secrets.op9_secrets,
        warc.op10_warc,
    )
}
ORACLES: dict[str, str] = {"op9_secrets": secrets.oracle(), "op10_warc": warc.oracle()}
