"""Part of alignspark: plans."""
