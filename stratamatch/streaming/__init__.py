"""Streaming forms of strata and effects."""
