"""The queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from .op1_language import op1_language_id
from .op2_packing import op2_nnls_packing
from .op3_tree import op3_kmeans_tree
from .op4_pii import op4_weak_pii
from .op5_pivots import ORACLE as OP5
from .op5_pivots import op5_pivot_table
from .op6_minhash import ORACLE as OP6
from .op6_minhash import op6_super_minhash
from .op7_lines import ORACLE as OP7
from .op7_lines import op7_line_dedup
from .op8_licenses import op8_license_scan
from .op9_suffixes import ORACLE as OP9
from .op9_suffixes import op9_suffix_array
from .op10_bpe import op10_bpe_encode_decode

QUERIES = {
    "op1_language_id": op1_language_id,
    "op2_nnls_packing": op2_nnls_packing,
    "op3_kmeans_tree": op3_kmeans_tree,
    "op4_weak_pii": op4_weak_pii,
    "op5_pivot_table": op5_pivot_table,
    "op6_super_minhash": op6_super_minhash,
    "op7_line_dedup": op7_line_dedup,
    "op8_license_scan": op8_license_scan,
    "op9_suffix_array": op9_suffix_array,
    "op10_bpe_encode_decode": op10_bpe_encode_decode,
}
ORACLES: dict[str, str] = {
    "op5_pivot_table": OP5,
    "op6_super_minhash": OP6,
    "op7_line_dedup": OP7,
    "op9_suffix_array": OP9,
}
