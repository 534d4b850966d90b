"""Tables, index storage and vector file formats."""
