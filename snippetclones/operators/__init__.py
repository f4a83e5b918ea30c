"""Clone, frequency, connection, statistics and review operators: functions between DataFrames."""
