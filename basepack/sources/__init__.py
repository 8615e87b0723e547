"""Tables, sequence views and text formats."""
