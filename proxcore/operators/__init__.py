"""Join and selection operators that the methods need beyond those of SQL."""
