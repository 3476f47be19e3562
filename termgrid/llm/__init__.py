"""Training-data operators: mixing, binary output, de-duplication, packing, filtering and scans.

Nothing else in the library imports this subpackage.
"""
