"""The queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from galoislake.llm import attribution, bytepairs, lines, neighbours, packing, quality, secrets, shingles, urls, vectors

QUERIES = {
    f.__name__: f
    for f in (
        quality.op1_quality, urls.op2_url_filter, neighbours.op3_neighbours, vectors.op4_vector_dedup, secrets.op5_secrets,
        packing.op6_packing, bytepairs.op7_byte_pairs, lines.op8_line_dedup, shingles.op9_jaccard_join, attribution.op10_token_counts,
    )
}
ORACLE = {"op2_url_filter": urls.SQL, "op4_vector_dedup": vectors.SQL, "op8_line_dedup": lines.SQL}
