"""Iterative plans: loops of DataFrame jobs whose lineage is cut between rounds."""
