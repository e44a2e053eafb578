"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from .htmltext import op9_htmltext
from .jaccard import op7_jaccard
from .licenses import OP3_SQL, op3_licenses
from .matroska import op8_matroska
from .packing import op4_packing
from .passages import op6_passages
from .pii import op1_pii
from .pieces import op2_pieces
from .quality import op10_quality
from .warc import OP5_SQL, op5_warc


def queries() -> dict:
    return {"op1_pii": op1_pii, "op2_pieces": op2_pieces, "op3_licenses": op3_licenses, "op4_packing": op4_packing, "op5_warc": op5_warc, "op6_passages": op6_passages, "op7_jaccard": op7_jaccard, "op8_matroska": op8_matroska, "op9_htmltext": op9_htmltext, "op10_quality": op10_quality}


def oracle_sql() -> dict[str, str]:
    return {"op3_licenses": OP3_SQL, "op5_warc": OP5_SQL}
