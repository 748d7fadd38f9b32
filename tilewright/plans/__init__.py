"""Layouts: tiles that cut a dataset into units of parallel work."""
