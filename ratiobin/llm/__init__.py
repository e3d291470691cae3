"""Training-data operators for text and vector tables; nothing outside this subpackage imports it."""
