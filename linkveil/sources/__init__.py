"""Tables, exchange files between parties, and the derived person registry."""
