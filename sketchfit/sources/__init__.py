"""Tables, dataset collections, sketch stores and generated datasets."""
