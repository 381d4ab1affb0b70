"""Part of alignspark: functions."""
