"""Training-data operators: classifiers, URL rules, deduplication, tokenisation and packing.

The rest of the library never imports this subpackage.
"""
