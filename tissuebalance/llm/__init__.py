"""Training-data operators: language ID, packing, search, PII, deduplication, licenses and BPE.

Nothing outside this subpackage (and the driver entry point, behind a guard) imports it.
"""
