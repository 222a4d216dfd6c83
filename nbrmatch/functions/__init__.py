"""Part of the matching engine."""
