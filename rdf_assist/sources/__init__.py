"""Tables, text formats and streams in and out."""
