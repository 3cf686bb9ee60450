"""Training-data operators: toxicity, deduplication, packing, token counts,
sampled segmentation, vector search, secret and license scans.

Nothing else in ``treefix`` imports this subpackage.
"""
