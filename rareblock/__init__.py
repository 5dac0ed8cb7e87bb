"""Candidate pairs for very large record sets, found by intersecting over-size blocks until they are small."""
