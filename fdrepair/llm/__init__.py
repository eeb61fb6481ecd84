"""Training-data operators: tokens, pages, media, language models, duplicates, filters and privacy.

Nothing outside this folder imports it; ``queries`` registers its operators.
"""
