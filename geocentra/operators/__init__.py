"""Relational operators that Spark lacks, as compositions of its own: orders without a global window, theta joins by distinct values."""
