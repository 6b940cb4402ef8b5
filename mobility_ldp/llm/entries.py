"""The queries of this subpackage, and the SQL that checks them."""

from . import chat, decontaminate, langid, licences, line_dedup, near_dedup, packing, pii, topk, urlrules


def queries():
    return {"op1_decontaminate": decontaminate.op1, "op2_minhash": near_dedup.op2, "op3_chat": chat.op3, "op4_url": urlrules.op4, "op5_licence": licences.op5, "op6_topk": topk.op6, "op7_line_dedup": line_dedup.op7, "op8_packing": packing.op8, "op9_pii": pii.op9, "op10_language": langid.op10}


def oracle_sql():
    return {"op1_decontaminate": decontaminate.SQL, "op2_minhash": near_dedup.SQL, "op3_chat": chat.SQL, "op4_url": urlrules.sql(), "op5_licence": licences.sql(), "op6_topk": topk.SQL, "op7_line_dedup": line_dedup.SQL}
