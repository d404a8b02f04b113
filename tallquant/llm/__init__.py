"""Training-data operators: search, scoring, dedup, decontamination, packing.

Nothing else in the library imports this subpackage, so it can be removed as a
whole.  Each module holds one operator with its own general interface;
:mod:`tallquant.llm.queries` holds the thin registered queries.
"""
