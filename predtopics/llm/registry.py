"""Queries over the given tables, by name, and SQL that says the same where SQL can."""

from __future__ import annotations

from . import decontaminate, secrets
from .bpe import op4_bpe
from .html_text import op9_html_text
from .language import op5_language
from .licenses import op1_licenses
from .neighbours import op7_neighbours
from .ngram_quality import op2_quality
from .simhash import op10_simhash
from .token_shards import op8_token_shards

QUERIES = {"op1_licenses": op1_licenses, "op2_quality": op2_quality, "op3_decontaminate": decontaminate.op3_decontaminate, "op4_bpe": op4_bpe, "op5_language": op5_language, "op6_secrets": secrets.op6_secrets, "op8_token_shards": op8_token_shards, "op7_neighbours": op7_neighbours, "op9_html_text": op9_html_text, "op10_simhash": op10_simhash}

ORACLES: dict[str, str] = {"op3_decontaminate": decontaminate.ORACLE, "op6_secrets": secrets.ORACLE}
