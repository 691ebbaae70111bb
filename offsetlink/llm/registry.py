"""The queries of the training-data operators, and SQL for those that SQL expresses."""

from offsetlink.llm import attention_lm, chat_format, grid_join, language_id, merge_dropout, secrets, shingle_join, toxicity, warc, winnowing

QUERIES = {
    "op1_merge_dropout": merge_dropout.op1_merge_dropout,
    "op4_language_id": language_id.op4_language_id,
    "op3_grid_join": grid_join.op3_grid_join,
    "op6_shingle_join": shingle_join.op6_shingle_join,
    "op7_attention_lm": attention_lm.op7_attention_lm,
    "op8_toxicity": toxicity.op8_toxicity,
    "op2_chat_format": chat_format.op2_chat_format,
    "op5_secrets": secrets.op5_secrets,
    "secrets_base": secrets.secrets_base,
    "op9_winnowing": winnowing.op9_winnowing,
    "op10_warc": warc.op10_warc,
}
ORACLES = {
    "op3_grid_join": grid_join.ORACLE_OP3,
    "op6_shingle_join": shingle_join.ORACLE_OP6,
    "op9_winnowing": winnowing.ORACLE_OP9,
    "op10_warc": warc.ORACLE_OP10,
    "secrets_base": secrets.ORACLE_BASE,
    "op2_chat_format": chat_format.ORACLE_OP2,
}
