"""What __spark_entry__ registers: queries and the SQL that gives the same rows."""
