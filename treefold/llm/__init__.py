"""Training-data operators: near and exact duplicates, line dedup, mixing,
classifiers, licence scans, fingerprints, packing and token files.

Nothing else in the package imports this subpackage.
"""
