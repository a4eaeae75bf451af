"""Methods to compare with, rebuilt from public literature."""
