"""The queries of this package and the SQL of those that SQL can express."""

from __future__ import annotations

from . import decontaminate, hamming_search, html_text, language_id, licenses, ngram_join, packing, quality, token_store, warc

MODULES = (decontaminate, ngram_join, warc, licenses, hamming_search, html_text, packing, language_id, quality, token_store)


def queries() -> dict:
    found = {}
    for module in MODULES:
        found |= {name: getattr(module, name) for name in dir(module) if name.startswith("op") and name[2:3].isdigit()}
    return found


def oracle_sql() -> dict[str, str]:
    found = {}
    for module in MODULES:
        found |= getattr(module, "SQL", {})
    return found
