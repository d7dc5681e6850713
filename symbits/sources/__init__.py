"""Tables, views and sets that queries run on."""
