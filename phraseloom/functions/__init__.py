"""Part of the phrase engine."""
