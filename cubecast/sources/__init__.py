"""cubecast.sources"""
