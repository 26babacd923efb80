"""Tables, files and the inputs built from them."""
