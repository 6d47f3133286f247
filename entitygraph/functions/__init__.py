"""The methods as functions: SQL functions, Arrow functions and table functions that a session can register."""
