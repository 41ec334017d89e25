"""Part of gsample."""
