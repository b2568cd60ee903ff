"""Part of cutline."""
