"""The queries of this subpackage by name, and the SQL that gives the same rows where SQL can."""

from __future__ import annotations

from .decontaminate import op8_decontaminate
from .line_dedup import op10_line_dedup
from .minhash import op3_minhash
from .oracles import ORACLE_SQL
from .packing import op1_packing
from .pseudonyms import op6_pseudonyms
from .toxicity import op9_toxicity
from .url_templates import op5_url_templates
from .vector_graph import op7_vector_graph
from .warc import op2_warc
from .wavelet import op4_wavelet

QUERIES = {f.__name__: f for f in (op1_packing, op2_warc, op3_minhash, op4_wavelet, op5_url_templates, op6_pseudonyms, op7_vector_graph, op8_decontaminate, op9_toxicity, op10_line_dedup)}

__all__ = ["ORACLE_SQL", "QUERIES"]
