"""Corpus operators: sharding, language id, chat formatting, token files and the like."""
