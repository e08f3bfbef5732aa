"""Operators that prepare text for language-model training, at corpus scale.

Nothing else in ``regsketch`` imports this subpackage.
"""
