"""Training-data operators: packing, decontamination, sharding, deduplication, classifiers, archives and scans.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries only when it is present.
"""
