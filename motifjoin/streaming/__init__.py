"""Changing relations fed by streams."""
