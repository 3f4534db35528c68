"""Operators for preparing training corpora; nothing else in ``setsync`` imports this subpackage."""
