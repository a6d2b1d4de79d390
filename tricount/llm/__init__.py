"""Training-data operators: extraction, sharding, scanning, classification, packing, search and de-duplication.

Nothing outside this subpackage imports it.
"""
