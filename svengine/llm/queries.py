"""The queries of this subpackage and the SQL that DuckDB holds against them."""

from __future__ import annotations

from .dedup import op8_exact_dedup
from .encoding import op4_bpe
from .fingerprint import op6_fingerprints
from .idfiles import op9_id_files
from .lmscore import op10_lm_scores
from .neardup import op2_near_dedup
from .packing import op5_packing
from .quality import op3_quality
from .sharding import op1_sharding
from .urls import op7_url_filter

QUERIES = {f.__name__: f for f in (op1_sharding, op2_near_dedup, op3_quality, op4_bpe, op5_packing, op6_fingerprints, op7_url_filter, op8_exact_dedup, op9_id_files, op10_lm_scores)}

ORACLES = {
    "op8_exact_dedup": """
        WITH t AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, text_sha256
        FROM t WINDOW w AS (PARTITION BY text_sha256)
    """,
}
