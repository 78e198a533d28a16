"""Chronological paths over edge streams."""
