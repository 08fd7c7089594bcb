"""Functions that programs call by name."""
