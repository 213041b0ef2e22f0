"""Tables, vector sets made from them, and a vector file format."""
