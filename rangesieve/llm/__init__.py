"""Training-data operators: sharding, deduplication, decontamination, filtering, mixing and redaction.

Nothing else in the library imports this subpackage.  Every operator takes and returns DataFrames, keeps its
state in data-sized tables rather than in the driver, and states what it does with nulls, ties and empty tables.
"""
