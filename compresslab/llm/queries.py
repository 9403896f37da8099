"""Queries of the ten operators, by name; oracle SQL where DuckDB can say the same."""

from . import bpe, decontaminate, language_id, near_copies, onebit_search, oracles, secrets, shards, toxicity, url_graph, warc

QUERIES = {
    "op1_url_trust_graph": url_graph.query,
    "op2_language_by_compression": language_id.query,
    "op3_one_bit_codes": onebit_search.query,
    "op4_warc_reassembly": warc.query,
    "op5_template_decontamination": decontaminate.query,
    "op6_secret_forest": secrets.query,
    "op7_weighted_minhash": near_copies.query,
    "op8_bpe_chunked": bpe.query,
    "op9_toxicity_nb_ngrams": toxicity.query,
    "op10_shard_vector_packing": shards.query,
}

ORACLES: dict[str, str] = {"op1_url_trust_graph": oracles.url_sql(), "op3_one_bit_codes": oracles.SEARCH, "op4_warc_reassembly": oracles.WARC}
