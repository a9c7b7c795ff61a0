"""Operators for preparing training text: the ten methods of the README's table.

Nothing outside this subpackage imports it.
"""
