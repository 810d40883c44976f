"""Column-type discovery over large collections of tables, as Spark plans."""
