"""treefix: rule programs over Spark tables, materialised and kept correct under updates.

``Reasoner`` (``treefix.session``) is the entry point.
"""
