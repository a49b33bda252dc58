"""Training-data operators: tokens, search, dedup, quality, chat, HTML, packing.

Nothing outside this subpackage imports it; the queries it offers are listed in
:mod:`corpuskit.llm.queries`.
"""
