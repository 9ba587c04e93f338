"""Functions callable from SQL: UDTF, grouped aggregate and Arrow UDFs."""
