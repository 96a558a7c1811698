"""Column functions of the control rule, and the same as SQL functions."""
