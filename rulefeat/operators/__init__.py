"""Counting, mining, selection, binning and sampling."""
