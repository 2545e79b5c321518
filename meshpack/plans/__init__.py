"""Chains of operators and the choice among their forms."""
