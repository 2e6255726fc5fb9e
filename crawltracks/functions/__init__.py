"""Column helpers: pure expressions over columns, evaluated in the JVM."""
