"""Queries of this subpackage and the SQL that must give the same rows."""

from __future__ import annotations

from cutseg.llm.hash_tree import op4_hash_tree
from cutseg.llm.license_scan import op8_license_patience
from cutseg.llm.media_columns import op6_media_jpeg
from cutseg.llm.mixing import op1_mixing
from cutseg.llm.ngram_join import OP3_SQL, op3_ngram_jaccard
from cutseg.llm.packing import op5_pack_ga
from cutseg.llm.pivot_index import OP2_SQL, op2_pivot_permutation
from cutseg.llm.toxicity import op9_toxicity_cnn
from cutseg.llm.url_filter import op10_sql, op10_url_filter
from cutseg.llm.warc import OP7_SQL, op7_warc_revisits

QUERIES = {
    "op1_mixing": op1_mixing,
    "op2_pivot_permutation": op2_pivot_permutation,
    "op3_ngram_jaccard": op3_ngram_jaccard,
    "op4_hash_tree": op4_hash_tree,
    "op5_pack_ga": op5_pack_ga,
    "op6_media_jpeg": op6_media_jpeg,
    "op7_warc_revisits": op7_warc_revisits,
    "op8_license_patience": op8_license_patience,
    "op9_toxicity_cnn": op9_toxicity_cnn,
    "op10_url_filter": op10_url_filter,
}
ORACLE_SQL = {
    "op2_pivot_permutation": OP2_SQL,
    "op3_ngram_jaccard": OP3_SQL,
    "op7_warc_revisits": OP7_SQL,
    "op10_url_filter": op10_sql(),
}
