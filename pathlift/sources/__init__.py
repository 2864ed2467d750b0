"""Where tables come from: the repository of candidate tables and its derived views."""
