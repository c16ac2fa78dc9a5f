"""Relational operators that Spark lacks or that workflows use often."""
