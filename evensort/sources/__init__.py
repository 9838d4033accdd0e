"""Tables, files, the study's input sequences and sorted sinks."""
