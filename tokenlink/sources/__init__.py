"""Tables, person views derived from them, and delivery formats."""
