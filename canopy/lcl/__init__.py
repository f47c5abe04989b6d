"""Locally checkable labellings on forests."""
