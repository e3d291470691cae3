"""Column formulas, bit packing and SQL functions of the codec."""
