"""Tables, files and ledgers."""
