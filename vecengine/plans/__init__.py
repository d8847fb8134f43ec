"""Choice of engine and the SQL that restates queries."""
