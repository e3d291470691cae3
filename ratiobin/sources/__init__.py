"""Series builders, table readers, the compressed store and the array-file format."""
