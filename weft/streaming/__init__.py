"""Incremental learning: a state of pairs and counts that batches and streams are folded into."""
