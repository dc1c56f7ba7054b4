"""Operators for preparing language-model training corpora; nothing else in the package imports this one."""
