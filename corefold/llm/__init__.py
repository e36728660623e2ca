"""Operators for preparing training text at scale. Nothing else in corefold imports this subpackage."""
