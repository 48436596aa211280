"""Tables, files and streams that graphs are built from."""
