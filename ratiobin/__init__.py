"""Error-bounded temporal ratio compression on Spark."""
