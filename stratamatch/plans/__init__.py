"""Descriptions that the operators compile: units, treatments, hops, causal graphs."""
