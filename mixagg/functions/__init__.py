"""Part of the mixed-aggregate engine."""
