"""Queries of this subpackage and their SQL."""

from segdedup.llm import embedding_dedup, mixing, packing, pii, quality_model, quality_rules, simhash, suffix_dedup, token_files, url_filter

MODULES = (suffix_dedup, mixing, quality_rules, token_files, url_filter, pii, packing, quality_model, simhash, embedding_dedup)


def queries() -> dict:
    import corpus_pipeline

    return {name: f for m in MODULES for name, f in m.QUERIES.items()} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, sql in m.ORACLE_SQL.items()}
