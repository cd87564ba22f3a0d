"""Operators for preparing training text at scale. Nothing outside this subpackage imports it."""
