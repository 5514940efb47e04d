"""Training-data operators: quality, near copies, decontamination, personal data, tokens, language, URLs, shards.

Every operator takes a DataFrame plus column names and keeps nothing in the driver that grows with the corpus.
Nothing outside this subpackage imports it.
"""
