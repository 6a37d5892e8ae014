"""Training-data operators (deduplication, filtering, tokenising, packing).

Nothing else in the library imports this subpackage, so it can be left out of
an installation; ``textredun.llm.queries`` lists its runnable queries.
"""
