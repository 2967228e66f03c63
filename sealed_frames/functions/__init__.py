"""Expressions over columns, grouped by kind; all are built on JVM functions."""
