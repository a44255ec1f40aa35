"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import class_lm, decontaminate, language_id, licenses, line_dedup, mtree, near_join, packing, pii, warc

QUERIES = {
    "op1_pii": pii.op1_pii,
    "op2_decontaminate": decontaminate.op2_decontaminate,
    "op3_line_dedup": line_dedup.op3_line_dedup,
    "op4_class_lm": class_lm.op4_class_lm,
    "op5_license_scan": licenses.op5_license_scan,
    "op6_exact_topk": mtree.op6_exact_topk,
    "op7_language_id": language_id.op7_language_id,
    "op8_packing": packing.op8_packing,
    "op9_warc": warc.op9_warc,
    "op10_near_join": near_join.op10_near_join,
}
SQL = {"op2_decontaminate": decontaminate.SQL, "op3_line_dedup": line_dedup.SQL, "op5_license_scan": licenses.SQL, "op6_exact_topk": mtree.SQL, "op9_warc": warc.SQL}
