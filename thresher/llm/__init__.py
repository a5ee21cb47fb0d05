"""Training-data operators: scoring, scanning, search, decontamination, binary output,
packing, chat rendering, near-duplicates and sharding.

Nothing else in the library imports this subpackage; ``entries`` lists its queries.
"""
