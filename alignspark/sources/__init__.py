"""Part of alignspark: sources."""
