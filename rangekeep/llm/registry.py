"""The text-corpus queries by name, with DuckDB SQL where it can say the same."""

from __future__ import annotations

from rangekeep.llm import html_text, lattice, line_dedup, mixing, ngram_join, packing, quality, secrets, toxicity, url_filter

QUERIES = {
    "op1_toxicity": toxicity.query,
    "op2_ngram_join": ngram_join.query,
    "op3_html_text": html_text.query,
    "op4_quality": quality.query,
    "op5_packing": packing.query,
    "op6_mixing": mixing.query,
    "op7_secrets": secrets.query,
    "op8_url_filter": url_filter.query,
    "op9_lattice": lattice.query,
    "op10_line_dedup": line_dedup.query,
}
SQL = {"op6_mixing": mixing.SQL, "op10_line_dedup": line_dedup.SQL}


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
