"""The compared methods as thin compositions of index, order and enumeration."""
