"""Chains, blocks, steps, extractions, solvers, diagnostics and measures."""
