"""Signatures of weighted sets on Spark: similarity, search and duplicate detection at scale."""
