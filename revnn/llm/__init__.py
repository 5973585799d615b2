"""Operators of a training-data pipeline. Nothing outside this subpackage imports it (but for the guarded entry point)."""
