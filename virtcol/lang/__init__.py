"""VSQL: a small SQL in which a quoted phrase stands for an attribute that is not stored."""
