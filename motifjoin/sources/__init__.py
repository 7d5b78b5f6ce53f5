"""Graphs and relations derived from tables, and readers and writers around them."""
