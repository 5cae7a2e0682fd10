"""Vector sets on the given tables, file formats, request streams."""
