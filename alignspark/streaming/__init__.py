"""Part of alignspark: streaming."""
