"""Tables, file formats and the graphs built from them."""
