"""graphstitch: enumeration of pattern graphs in large data graphs by stitching motif tables with relational joins."""
