"""Spark-native engine for semantic trie overlays: profiles, soft binary trie, peer lists, routing, measures."""

__version__ = "0.1.0"
