"""Training-data operators: packing, deduplication, extraction, scans, quality, joins, sharding.

Nothing outside this subpackage imports it.  ``registry.queries`` and ``registry.oracle_sql``
hold what the driver runs; every operator has its own module and a general interface.
"""
