"""Part of alignspark: operators."""
