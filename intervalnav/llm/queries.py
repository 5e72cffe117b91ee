"""All queries of this subpackage and their SQL."""

from __future__ import annotations

from . import queries_bytebpe, queries_fingerprint, queries_flac, queries_gatedlm, queries_htmltext, queries_jaccard, queries_langid, queries_linededup, queries_packing, queries_urlfilter

_MODULES = (queries_langid, queries_bytebpe, queries_htmltext, queries_jaccard, queries_linededup, queries_gatedlm, queries_urlfilter, queries_flac, queries_fingerprint, queries_packing)
QUERIES = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
SQL = {k: v for m in _MODULES for k, v in m.SQL.items()}
