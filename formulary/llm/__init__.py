"""Training-data operators: near-duplicate removal, token counts, filters, classifiers, media, packing and mixing.

Nothing outside this package imports it.
"""
