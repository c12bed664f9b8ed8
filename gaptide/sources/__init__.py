"""Tables, file formats and feature recipes."""
