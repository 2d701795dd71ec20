"""Readers and writers of operators and systems, and the generated source of structure constants."""
